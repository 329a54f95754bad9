"""Training-data operators: one module per operator, and ``queries`` which registers them.

Nothing outside this subpackage imports it.
"""
