"""The model, its inference and learning, ranking and measures."""
