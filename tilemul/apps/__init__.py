"""Applications that use the two kernels."""
