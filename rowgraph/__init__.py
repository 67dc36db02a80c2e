"""Learning over linked tables, written for Spark."""
