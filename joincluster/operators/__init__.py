"""The clustering method, its variants, baselines and measures."""
