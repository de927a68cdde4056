"""Where words come from and where verdicts go."""
