"""Quantization, paths, bit vectors and variable-length codes."""
