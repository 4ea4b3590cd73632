"""Vector functions as Catalyst expressions, aggregates and SQL functions."""
