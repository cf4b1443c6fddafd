"""Training-data operators: ten corpus operators, their queries and their reference SQL.

Nothing outside this subpackage imports it.
"""
