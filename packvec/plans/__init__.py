"""Whole procedures: index, search, baselines, measures, dispatch, cost."""
