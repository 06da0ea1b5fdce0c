"""Registered queries: methods, measures and workloads, and the relational operators around them."""
