"""Training-data operators: one module for each operator, ``catalog`` for their queries.

Nothing outside this subpackage imports it.
"""
