"""Similarity joins that choose their own threshold, and the operators around them, as Spark plans."""
