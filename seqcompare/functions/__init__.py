"""Alignment-free pair functions: those over histograms, the sketch distance and the spaced-word distance."""
