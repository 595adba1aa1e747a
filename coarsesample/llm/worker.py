"""What a Python worker keeps between tasks.

Workers live on from stage to stage, and so do their caches. An operator claims the worker before it
fills a cache; the caches of the operator before it are emptied then, so that a pipeline's stages
don't add up in memory.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable

_caches: dict[str, Callable[[], None]] = {}
_owner = [""]


def claim(name: str, clear: Callable[[], None]) -> None:
    """Make ``name`` the worker's user; ``clear`` empties its cache later."""
    if _owner[0] == name:
        return
    for other, empty in list(_caches.items()):
        if other != name:
            empty()
            del _caches[other]
    _caches[name], _owner[0] = clear, name
    gc.collect()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library: memory is given back later
        pass
