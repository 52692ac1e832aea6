"""Search, reductions, bounds, orders, preprocessing, baselines and measures."""
