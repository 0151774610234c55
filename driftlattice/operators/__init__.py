"""Relational and counting operators."""
