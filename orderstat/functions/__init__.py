"""What users call: quantiles and their relatives, SQL entry points, later batches of ranks."""
