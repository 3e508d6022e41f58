"""Batching, sketches, forests, caches, certificates, cuts and the exact baselines."""
