"""rootfinal: tree aggregation over DataFrames whose root finalizes on an executor, and what builds on it."""
