"""Private approximate distinct counting on Spark."""
