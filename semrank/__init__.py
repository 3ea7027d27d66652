"""Semantic ORDER BY and top-K over Spark DataFrames with listwise rankers."""
