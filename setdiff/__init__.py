"""Finding the difference of two large sets by exchanging small mergeable sketches, on Spark."""
