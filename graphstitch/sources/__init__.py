"""Data graphs and where they come from."""
