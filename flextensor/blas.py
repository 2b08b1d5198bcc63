"""One BLAS thread in every process: tasks share the cores already, and on the driver OpenBLAS' own threads were seen to
stall small solves for minutes."""

from __future__ import annotations

import ctypes
import os

SETTERS = ("scipy_openblas_set_num_threads64_", "scipy_openblas_set_num_threads", "openblas_set_num_threads64_", "openblas_set_num_threads")


def one_thread() -> bool:
    """Whether a loaded OpenBLAS was told so; elsewhere the environment does it for libraries loaded later."""
    for name in ("OPENBLAS_NUM_THREADS", "OMP_NUM_THREADS", "MKL_NUM_THREADS"):
        os.environ.setdefault(name, "1")
    import numpy  # noqa: F401  loads its library

    try:
        with open("/proc/self/maps") as f:
            paths = {line.split()[-1] for line in f if "openblas" in line}
    except OSError:
        return False
    done = False
    for path in paths:
        try:
            lib = ctypes.CDLL(path)
        except OSError:
            continue
        for name in SETTERS:
            if hasattr(lib, name):
                getattr(lib, name)(1)
                done = True
                break
    return done
