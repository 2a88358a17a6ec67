"""Pattern queries over uncertain entity graphs on Spark."""
