"""Training-data operators: text, archive and token steps that stand beside the graph engine.

Nothing outside this subpackage imports it.
"""
