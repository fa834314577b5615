"""Declarative pipelines of semantic operators over document collections, on Spark."""
