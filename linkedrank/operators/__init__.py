"""Distributed evaluation of networks, baselines and maintenance."""
