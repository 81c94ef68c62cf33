"""Micro-batch maintenance of ranks, and event-time operators."""
