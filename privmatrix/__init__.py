"""Private multi-dimensional frequency matrices on Spark."""
