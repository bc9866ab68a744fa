"""Nearest neighbours under numeric range filters, as DataFrame plans and Arrow kernels."""
