"""Readers of crawls and table lakes, writers for trainers."""
