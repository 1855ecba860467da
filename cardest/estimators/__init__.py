"""Estimating selectivities from samples, and counting them exactly."""
