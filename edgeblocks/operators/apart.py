"""A run in a process of its own, for its time and memory alone."""

from __future__ import annotations

import json
import mmap
import os
import resource
import time
from collections.abc import Callable

import numpy as np


def _resident() -> int:
    """Bytes of this process in memory."""
    with open("/proc/self/statm", encoding="ascii") as f:
        return int(f.read().split()[1]) * os.sysconf("SC_PAGE_SIZE")


def run_apart(size: int, run: Callable[[dict], np.ndarray]) -> tuple[np.ndarray | None, dict]:
    """(result, figures) of run, which returns size whole numbers and may fill the dict it gets with figures of its own.

    The run happens in a forked child: its peak is what it needs beyond what the parent held, and nothing of an earlier run counts. A
    run that fails gives None and the reason under "error". Figures: seconds, peak_bytes, and the run's own.
    """
    shared = mmap.mmap(-1, max(4 * size, 4))
    read, write = os.pipe()
    child = os.fork()
    if child == 0:
        figures: dict = {}
        try:
            os.close(read)
            before = _resident()
            began = time.perf_counter()
            got = run(figures)
            figures["seconds"] = time.perf_counter() - began
            figures["peak_bytes"] = max(0, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss * 1024 - before)
            np.frombuffer(shared, np.int32, size)[:] = got
        except BaseException as e:  # noqa: BLE001  the child must not go on as a second worker
            figures = {"error": f"{type(e).__name__}: {e}"[:300]}
        finally:
            with os.fdopen(write, "w") as f:
                json.dump(figures, f)
            os._exit(0)
    os.close(write)
    with os.fdopen(read) as f:
        told = f.read()
    os.waitpid(child, 0)
    figures = json.loads(told) if told else {"error": "the run's process ended"}
    return (None if "error" in figures else np.frombuffer(shared, np.int32, size).copy()), figures
