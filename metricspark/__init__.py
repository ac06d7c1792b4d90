"""metricspark: exact similarity search in metric spaces, written for Spark."""
