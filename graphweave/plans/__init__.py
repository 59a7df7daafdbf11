"""Specifications of aggregations and the choice of a physical form for them."""
