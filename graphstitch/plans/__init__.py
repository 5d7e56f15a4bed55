"""Driver-side planning: patterns, motifs, tilings, estimates and SQL text."""
