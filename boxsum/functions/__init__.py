"""Measures of cost and accuracy, and user-defined functions."""
