"""Private answers to batches of linear counting queries, on Spark."""
