"""Grammars of streams."""
