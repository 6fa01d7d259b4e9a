"""A run-length relational engine on Spark: sorted projections stored as run tables, and query rewriting over them."""
