"""Training-data operators: one module per operator, queries in `queries.py`.

Nothing outside this subpackage imports it; removing the folder leaves the rest
of the library working.
"""
