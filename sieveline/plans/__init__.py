"""Pipelines as immutable plans, the thirteen rewrite directives and the optimizer."""
