"""Operators on edge-labelled digraphs."""
