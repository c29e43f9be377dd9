"""Exact triangle counting and the network measures built on it, as Spark DataFrame plans."""
