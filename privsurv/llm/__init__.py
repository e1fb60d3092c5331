"""Training-data operators for very large text tables.

Nothing else in the library imports this subpackage.  Each module has one
operator with a general interface; ``queries`` derives the registered queries.
"""
