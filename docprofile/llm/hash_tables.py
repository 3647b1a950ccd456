"""Tables of numbers by hashed names: sorted arrays in files of the shared folder, cut by ranges of names, that workers map.

A file holds a range's sorted names (whole, or their low 32 bits and where each value of the upper bits begins) and its
columns, a byte a number with the larger ones listed apart. Whoever looks names up maps the files that these fall in.
"""

from __future__ import annotations

import json
import os
from collections import OrderedDict

import numpy as np

from .common import file_system

#: Files of a table that a worker keeps mapped; bytes that it keeps of a table in a store that can't be mapped.
MAPS, HELD_BYTES = 2048, 256 << 20


def part_of(keys: np.ndarray, bits: int, ranges: int) -> np.ndarray:
    """Range of each name of so many bits, by its upper 32 bits."""
    top = keys >> np.uint64(bits - 32) if bits > 32 else keys << np.uint64(32 - bits)
    return ((top * np.uint64(ranges)) >> np.uint64(32)).astype(np.int64)


def stretches(part: np.ndarray):
    """(range, from, to) of each stretch of a sorted array of ranges: ranges without names cost nothing."""
    first = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1]))) if len(part) else np.zeros(0, int)
    return zip(part[first].tolist(), first.tolist(), [*first[1:].tolist(), len(part)], strict=False)


def save(folder: str, name: str, arrays: dict[str, np.ndarray]) -> None:
    """Arrays as one file: under a name of its own first, so that a retried or doubled task leaves the same whole file."""
    import uuid

    head, at = {}, 0
    for k, a in arrays.items():
        head[k] = (a.dtype.str, len(a), at)
        at += -(-a.nbytes // 8) * 8
    text = json.dumps(head).encode()
    text += b" " * (-len(text) % 8)
    fs, to = file_system(folder)
    own = f"{to}/{name}.{uuid.uuid4().hex}"
    with fs.open_output_stream(own) as f:
        f.write(len(text).to_bytes(8, "little") + text)
        for a in arrays.values():
            f.write(memoryview(np.ascontiguousarray(a)).cast("B"))
            f.write(bytes(-a.nbytes % 8))
    fs.move(own, f"{to}/{name}")


class Files:
    """Arrays of a model's files, mapped; of a store that can't be mapped, the files used last are held."""

    def __init__(self, folder: str):
        from pyarrow import fs as pfs

        self.fs, self.at = file_system(folder)
        self.local, self.open, self.bytes = isinstance(self.fs, pfs.LocalFileSystem), OrderedDict(), 0

    def __call__(self, name: str) -> dict[str, np.ndarray] | None:
        """None if a range has no name, and so no file."""
        if name in self.open:
            self.open.move_to_end(name)
            return self.open[name][0]
        path, whole = f"{self.at}/{name}", None
        if self.local:
            whole = np.memmap(path, np.uint8, "r") if os.path.exists(path) else None
        elif self.fs.get_file_info(path).is_file:
            with self.fs.open_input_file(path) as f:
                whole = np.frombuffer(f.read(), np.uint8)
        arrays, size = None, 0 if whole is None or self.local else len(whole)
        if whole is not None:
            n = int(whole[:8].view("<u8")[0])
            body = whole[8 + n :]
            arrays = {k: np.asarray(body[at : at + np.dtype(kind).itemsize * count]).view(kind) for k, (kind, count, at) in json.loads(bytes(whole[8 : 8 + n])).items()}
        self.open[name] = (arrays, size)
        self.bytes += size
        while len(self.open) > MAPS or (self.bytes > HELD_BYTES and len(self.open) > 1):
            self.bytes -= self.open.popitem(last=False)[1][1]
        return arrays


def table(keys: np.ndarray, columns: dict[str, np.ndarray], wide: bool) -> dict[str, np.ndarray]:
    """What a range's file holds."""
    if wide:
        out = {"keys": keys}
    else:
        high = (keys >> np.uint64(32)).astype(np.int64)
        first = int(high[0])
        starts = np.searchsorted(high, np.arange(first, int(high[-1]) + 2)).astype(np.uint32)
        out = {"low": keys.astype(np.uint32), "first": np.array([first], np.int64), "starts": starts}
    for name, c in columns.items():
        c = c.astype(np.uint64)
        large = np.flatnonzero(c >= 255)
        out |= {name: np.minimum(c, 255).astype(np.uint8), f"{name}-at": large.astype(np.uint32), f"{name}-is": c[large]}
    return out


def found(t: dict[str, np.ndarray], keys: np.ndarray) -> np.ndarray:
    """Place of each sorted name in a range's table, -1 if it has none."""
    if "keys" in t:
        at = np.minimum(np.searchsorted(t["keys"], keys), len(t["keys"]) - 1)
        return np.where(t["keys"][at] == keys, at, -1)
    low, starts = t["low"], t["starts"]
    high = (keys >> np.uint64(32)).astype(np.int64) - t["first"][0]
    here = (high >= 0) & (high < len(starts) - 1)
    high = np.where(here, high, 0)
    a, b, want = starts[high].astype(np.int64), starts[high + 1].astype(np.int64), keys.astype(np.uint32)
    end = b.copy()
    for _ in range(int((b - a).max(initial=0)).bit_length()):
        mid = (a + b) >> 1
        less = low[np.minimum(mid, len(low) - 1)] < want
        a, b = np.where(less & (mid < b), mid + 1, a), np.where(less, b, mid)
    at = np.minimum(a, len(low) - 1)
    return np.where(here & (a < end) & (low[at] == want), at, -1)


def numbers(t: dict[str, np.ndarray], name: str, at: np.ndarray) -> np.ndarray:
    """Numbers of a table at some places."""
    out = t[name][at].astype(np.float64)
    large = np.flatnonzero(out == 255)
    if len(large):
        out[large] = t[f"{name}-is"][np.searchsorted(t[f"{name}-at"], at[large])]
    return out
