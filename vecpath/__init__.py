"""vecpath: mixed vector-relational search and analytics on Spark."""
