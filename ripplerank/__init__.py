"""Personalised PageRank at scale, declared as Spark DataFrame plans."""
