"""One mapped copy of a broadcast array for all Python workers of an executor."""

from __future__ import annotations

import fcntl
import os

import numpy as np


def mapped(held, name: str) -> np.ndarray:
    """The broadcast array as a read-only memory map of one file in the executor's own folder.

    The first worker unpickles the broadcast and writes the file under a lock; the others only map it, so an executor holds the array once however many workers it runs. The
    file is scratch that any executor makes anew; files of earlier multiplies are unlinked, and the folder goes with the executor.
    """
    from pyspark import SparkFiles

    folder = os.path.join(SparkFiles.getRootDirectory() or ".", "resident")
    os.makedirs(folder, exist_ok=True)
    path = os.path.join(folder, f"{name}.npy")
    with open(os.path.join(folder, f"{name}.lock"), "w") as lock:
        fcntl.flock(lock, fcntl.LOCK_EX)
        if not os.path.exists(path):
            np.save(path + ".draft.npy", np.ascontiguousarray(held.value))
            os.rename(path + ".draft.npy", path)
            held.unpersist() if hasattr(held, "_sc") and held._sc else None
            for other in os.listdir(folder):
                if other.split("-")[0] == name.split("-")[0] and other.endswith(".npy") and int(other.split("-")[1].split(".")[0]) < int(name.split("-")[1]) - 1:
                    os.unlink(os.path.join(folder, other))
    return np.load(path, mmap_mode="r")


_buffers: dict[str, np.ndarray] = {}


def zeros(rows: int, width: int, reuse: bool = True) -> np.ndarray:
    """A zeroed (rows, width) buffer; with reuse it is a part of one that the worker keeps and only makes larger when it must."""
    if not reuse:
        return np.zeros((rows, width))
    held = _buffers.get("out")
    if held is None or held.size < rows * width:
        held = _buffers["out"] = np.empty(rows * width)
    out = held[: rows * width].reshape(rows, width)
    out.fill(0.0)
    return out
