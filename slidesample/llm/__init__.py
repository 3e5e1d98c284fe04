"""Training-data operators.  Nothing outside this subpackage imports it.

`queries()` and `oracle_sql()` in `registry` list the queries `op1_…` to `op10_…` and `pipeline`.
"""
