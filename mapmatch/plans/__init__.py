"""Plan choice, pattern corpora and the registered workloads."""
