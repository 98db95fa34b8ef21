"""Hypergraphs from event streams, and standing pattern queries over them."""
