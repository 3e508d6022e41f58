"""Hash families and sampler kernels."""
