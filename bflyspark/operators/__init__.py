"""Methods: wedges, dominance counts, indexes, estimators, baselines, measures."""
