"""Enforcement strategies: each rewrites a plan so that every output tuple carries verdicts."""
