"""One matrix-library thread per task slot: more would compete with the other slots."""

from __future__ import annotations

import ctypes

_done = False


def single_thread() -> None:
    """Set the loaded OpenBLAS of this process to one thread (no effect with other libraries)."""
    global _done
    if _done:
        return
    _done = True
    import numpy  # noqa: F401  loads the library

    try:
        with open("/proc/self/maps") as maps:
            paths = {line.split()[-1] for line in maps if "openblas" in line and ".so" in line}
    except OSError:
        return
    for path in paths:
        library = ctypes.CDLL(path)
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "scipy_openblas_set_num_threads", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)
                break
