"""Operations of a training-data pipeline: filters, deduplication, search, tokens and packing.

Each operator is one module; `registry` lists the queries that the entry file adds.
"""
