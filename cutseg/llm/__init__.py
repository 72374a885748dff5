"""Operators for large training corpora; nothing else in cutseg imports this."""
