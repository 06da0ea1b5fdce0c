"""Counting acyclic patterns in graphs whose nodes keep their edges private, on Spark."""
