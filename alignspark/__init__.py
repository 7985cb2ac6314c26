"""Progressive multiple alignment of symbol sequences on Spark."""
