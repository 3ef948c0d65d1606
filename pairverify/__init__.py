"""Pairs of structured graph queries and questions: building, verifying, cleaning and reporting on Spark."""
