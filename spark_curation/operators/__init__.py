"""Operators on pages, programs, documents and scores."""
