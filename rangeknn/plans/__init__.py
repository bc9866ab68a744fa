"""Registered workloads."""
