"""Column functions for sparse vectors, histograms and boxes."""
