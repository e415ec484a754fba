"""Labelled tables, edits against labels, readers and writers."""
