"""Training-data operators: ten text and vector operators beside the graph engine.

Nothing outside this subpackage imports it.
"""
