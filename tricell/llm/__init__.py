"""Operators that prepare training data: one module per operator.

Nothing outside this subpackage imports it.  `queries.py` holds the thin
`opN_*` queries and the SQL they are compared with.
"""
