"""Regularised empirical risk minimisation from private gradients."""
