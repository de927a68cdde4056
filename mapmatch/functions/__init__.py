"""SQL functions over automata."""
