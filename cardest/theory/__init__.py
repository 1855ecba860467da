"""Capacity dimensions of query classes and the sample sizes that follow from them."""
