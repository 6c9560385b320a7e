"""SQL answer grading on Spark."""
