"""Baselines that the index is measured against."""
