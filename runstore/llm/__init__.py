"""Training-data operators: near-dedup, tokenizing, sharding, filtering, decontamination.

Nothing outside this subpackage imports it.  `registry.queries()` and
`registry.oracle_sql()` list the thin queries that `__spark_entry__.py` adds.
"""
