"""Distinct counting from samples spread over many sites, on Spark."""
