"""Expressions and measures."""
