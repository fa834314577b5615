"""Inputs, reference answers and plans of the experiment workloads on the given tables."""
