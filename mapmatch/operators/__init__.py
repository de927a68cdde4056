"""Chunking, scanning, folding and measuring as DataFrame operators."""
