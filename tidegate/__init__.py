"""Selective data-parallel training on Spark: sizing, gate, loss-weighted merge, baselines and measures."""
