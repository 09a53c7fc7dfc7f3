"""Predicate-topic analytics on Spark: facts, similarity of predicates, topic trees, woven queries."""
