"""Registered queries: the study's workloads, and the operators around them."""
