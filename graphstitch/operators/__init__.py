"""Relational execution: motif tables, stitching, semantics, scoring, baselines."""
