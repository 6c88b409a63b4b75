"""Whole pipelines, planted recordings, corruptions and experiments."""
