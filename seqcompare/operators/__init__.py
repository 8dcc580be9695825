"""Operators of the comparison pipeline: statistics, filters, normalisation, null models, significance, noise, trees."""
