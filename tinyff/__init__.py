"""Spark-native engine of very small feed-forward text models."""

import os

# Matrices here are small: one BLAS thread a process is faster, and tasks do not crowd each other.
for _name in ("OMP_NUM_THREADS", "OPENBLAS_NUM_THREADS", "MKL_NUM_THREADS"):
    os.environ.setdefault(_name, "1")
