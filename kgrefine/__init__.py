"""Spark-native refinement of documents into a governed knowledge graph."""
