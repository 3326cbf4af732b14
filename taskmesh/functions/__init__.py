"""Column and NumPy functions."""

from taskmesh.functions.draws import portable_uniform, uniform_for
from taskmesh.functions.vectors import add, axpy, clip, dot, norm2, scale, zeros

__all__ = ["add", "axpy", "clip", "dot", "norm2", "portable_uniform", "scale", "uniform_for", "zeros"]
