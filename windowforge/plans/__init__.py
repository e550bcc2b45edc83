"""Whole plans and the queries over them."""
