"""Split search: histograms, prefix scans, samplers, exact and approximate searches, trees."""
