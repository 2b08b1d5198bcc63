"""Spark-native nonlinear tensor factorization engine."""

from .blas import one_thread

one_thread()
