"""Grid-density clustering of very large point sets, written for Spark."""
