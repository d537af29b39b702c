"""Operators that prepare text corpora for training, each a function over DataFrames."""
