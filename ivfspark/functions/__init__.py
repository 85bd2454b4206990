"""Vector functions: Catalyst expressions, numpy kernels, packing."""
