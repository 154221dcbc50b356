"""Even, token-budgeted batches of many small graphs, and their coupling kernels, on Spark."""
