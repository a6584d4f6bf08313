"""Tokenisation and windows over streams."""
