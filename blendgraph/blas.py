"""One BLAS thread a process. The matrices here are small and tasks run side by side: more threads wait for each other's
cores, and on a full machine a small inverse takes a thousand times as long."""

from __future__ import annotations

import ctypes
from pathlib import Path

import numpy as np


def one_thread() -> bool:
    """-> whether a bundled OpenBLAS was told so."""
    found = False
    for path in (Path(np.__file__).parent.parent / "numpy.libs").glob("*openblas*"):
        lib = ctypes.CDLL(str(path))
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "openblas_set_num_threads"):
            if hasattr(lib, name):
                getattr(lib, name)(1)
                found = True
                break
    return found
