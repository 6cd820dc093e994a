"""Operators of a training-data pipeline: packing, rules, token counts, mixing, classifiers, deduplication, ids, shards.

Nothing else in gridmin imports this package. Each module holds one operator with its own interface;
``queries`` derives the registered result tables from them.
"""
