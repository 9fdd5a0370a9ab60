"""Query-centred temporal community search on Spark."""
