"""Proximity graphs: layered, single-layer, and their walks."""
