"""Tokenizers, dictionaries, intervals, comparisons, evaluation."""
