"""Dictionary compression of short-string columns on Spark."""
