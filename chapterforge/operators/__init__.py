"""Operators: filtering, pairs, judging, alignment, selection, retrieval, language models, measures."""
