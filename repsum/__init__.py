"""repsum: representative summaries of large analytical query logs on Spark."""
