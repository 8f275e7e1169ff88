"""Finding small sets of items that explain a database of baskets, on Spark."""
