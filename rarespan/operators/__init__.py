"""Operators on series, tokens, grammars and curves."""
