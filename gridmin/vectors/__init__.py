"""Block-partitioned vectors: ``Vec`` handles over (block_id, values) DataFrames, and operations on them."""

from gridmin.vectors import layout, ops
from gridmin.vectors.vec import Vec, concat, fill, from_expr, from_long, stack, uniform, zeros

__all__ = ["Vec", "concat", "fill", "from_expr", "from_long", "layout", "ops", "stack", "uniform", "zeros"]
