"""Automata over streams."""
