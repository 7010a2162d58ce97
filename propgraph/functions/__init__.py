"""Measures of cost and accuracy."""
