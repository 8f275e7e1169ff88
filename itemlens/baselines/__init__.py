"""Methods to compare with."""
