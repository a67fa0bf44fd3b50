"""Attention-guided context reduction and its experiment suite on Spark."""
