"""Scalar, array and vector functions, and the numeric kernels of the operators."""
