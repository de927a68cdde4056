"""Patterns, automata and map automata: numpy and plain Python, no Spark."""
