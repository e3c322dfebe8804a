"""Vector expressions and distance kernels."""
