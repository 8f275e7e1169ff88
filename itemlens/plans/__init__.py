"""Planning, experiment workloads and reports."""
