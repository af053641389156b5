"""placelink: linking records of places on Spark."""
