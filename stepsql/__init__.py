"""Step-reward analytics on Spark."""
