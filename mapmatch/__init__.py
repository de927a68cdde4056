"""Chunk-parallel automaton matching on Spark."""
