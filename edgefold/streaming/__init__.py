"""Folds over edges that arrive as a stream."""
