"""Crawls that keep arriving."""
