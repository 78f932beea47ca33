"""One BLAS thread for each process: tasks are the unit of parallelism.

Threads of the BLAS library that were started before a fork may never answer
afterwards, so the driver and the workers both keep to one.
"""

from __future__ import annotations

import ctypes
import glob
import os

import numpy as np

_SETTERS = ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "openblas_set_num_threads")


def one_thread() -> None:
    """Tells numpy's own OpenBLAS to use one thread; a numpy without it is left alone."""
    for path in glob.glob(os.path.join(os.path.dirname(os.path.dirname(np.__file__)), "numpy.libs", "*openblas*")):
        library = ctypes.CDLL(path)
        for name in _SETTERS:
            if hasattr(library, name):
                getattr(library, name)(1)
                break


one_thread()
