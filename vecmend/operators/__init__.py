"""Ground truth, graphs, search, mending, upkeep and measures."""
