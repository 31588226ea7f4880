"""Builds and evaluates training corpora for models of data analytics, on Spark."""
