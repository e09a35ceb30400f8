"""querygrade: grading of machine-written spatial SQL with Spark."""
