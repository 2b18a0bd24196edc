"""Training-data operators: ten operators, their queries and their SQL.

Nothing outside this subpackage imports it.
"""
