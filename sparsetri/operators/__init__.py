"""Exact counts, sampling passes, estimators, baselines and structural measures of edge relations."""
