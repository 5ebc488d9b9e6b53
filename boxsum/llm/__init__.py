"""Operators for training-data pipelines: each module holds one, `queries` registers them."""
