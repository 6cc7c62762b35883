"""Matching and match counts on streams of files."""
