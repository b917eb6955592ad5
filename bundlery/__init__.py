"""Package queries over large tables, answered with Spark."""
