"""Operators on cell domains: geometry, zoning, kernels, attacks and measures."""
