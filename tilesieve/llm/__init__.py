"""Training-data operators: one module for each, and their queries in ``registry``.

Nothing else in the library imports this subpackage.
"""
