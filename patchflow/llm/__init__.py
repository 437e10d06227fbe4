"""Training-data operators: one module per operator, queries in ``queries``.

Nothing else in the library imports this subpackage.  Operators are plain
functions from DataFrames to DataFrames; ``queries`` derives the digest columns
of the contract from their real outputs.
"""
