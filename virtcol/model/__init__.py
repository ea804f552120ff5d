"""Semantic models: what judges one row, and offline stand-ins for it."""
