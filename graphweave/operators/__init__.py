"""Aggregation, partitioning, synchronisation, training and their measures."""
