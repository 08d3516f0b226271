"""Formal-concept mining for Spark.

`sources` builds contexts from tables and text files, `functions` holds the column expressions on packed
attribute sets, `operators` the derivations, closures and mining methods, `plans` the round engine, the
named queries and measures, `streaming` the maintenance of concept families over growing data.
"""
