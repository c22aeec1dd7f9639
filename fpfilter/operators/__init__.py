"""Filters: specifications, kernels, building, probing, joins."""
