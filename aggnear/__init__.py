"""Exact top-k group proximity search on Spark, with a subpackage of corpus operators."""
