"""Schemes and experiments: one plan per workload."""
