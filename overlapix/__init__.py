"""Search for the sets that overlap a query set the most, on Spark."""
