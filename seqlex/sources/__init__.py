"""Readers of tables and of sequence, interval and matrix text files."""
