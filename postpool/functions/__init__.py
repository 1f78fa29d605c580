"""Expressions and byte kernels: analysis, block codecs, schedule arithmetic."""
