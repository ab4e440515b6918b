"""Progressive record matching on Spark: filter, weight, schedule, match."""
