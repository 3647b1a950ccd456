"""Local fold: each task folds its documents into one state a typed path, in one pass, for all monoids at once.

Nodes of a chunk of documents are gathered by typed path (one append a node) and each path's values are then reduced with
whole-list operations. What leaves a task is schema-sized: states of paths, distinct key sets, example slots, divisors and
the blocks of membership filters. The states are those of `monoids`, sketches included, so the same merges reduce them.
Only monoids of the user's own, or sketches of other sizes, are computed from facts instead.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from json.encoder import encode_basestring

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.formats import FORMATS
from .flatten import canonical, canonical_number, label_tag, parse_strict, step_text
from .sketches import Bins, Bloom, Hll, bloom_size, hash_texts

#: Column monoids that the fold computes.
FOLDED = ("count", "maxmin_number", "maxmin_string", "maxmin_array", "unique", "pattern", "format", "stats", "hll", "histogram")
#: Documents of a chunk; paths, key sets or filter blocks after which a task sends what it has and starts anew.
CHUNK, FLUSH, FLUSH_BLOCKS = 2000, 100_000, 20_000
STATE = (
    "part string, typed_path string, path string, parent_typed_path string, step string, kind string, tag string, n long, number_min double, number_max double, string_min int, string_max int, array_min int, array_max int, "
    "all_unique boolean, str_lo string, str_hi string, rev_lo string, rev_hi string, fmt_all long, fmt_n long, fmt_lo string, fmt_hi string, st_n long, st_mean double, st_m2 double, st_m3 double, st_m4 double, hll binary, "
    "keys array<string>, slot long, key long, example string, divisor long, integers boolean, bits binary, bins array<struct<x:double,y:double>>"
)
NAMES = [c.split()[0] for c in STATE.split(", ")]
_ARROW = {
    "string": pa.string(), "long": pa.int64(), "double": pa.float64(), "int": pa.int32(), "boolean": pa.bool_(), "binary": pa.binary(), "array<string>": pa.list_(pa.string()),
    "array<struct<x:double,y:double>>": pa.list_(pa.struct([("x", pa.float64()), ("y", pa.float64())])),
}
TYPES = [_ARROW[c.split(" ", 1)[1]] for c in STATE.split(", ")]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class State:
    """The state of one path in one task."""

    __slots__ = ("n", "num", "string", "array", "uniq", "ends", "fmt", "st", "gcd", "keys", "slots", "hll", "bloom", "bins")

    def __init__(self):
        self.n, self.keys, self.slots = 0, Counter(), {}
        self.num = self.string = self.array = self.uniq = self.ends = self.fmt = self.st = self.gcd = self.hll = self.bloom = self.bins = None

    def fields(self) -> dict:
        """What a row of state holds, by column."""
        out = {"n": self.n, "all_unique": self.uniq}
        for names, values in (
            (("number_min", "number_max"), self.num), (("string_min", "string_max"), self.string), (("array_min", "array_max"), self.array), (("str_lo", "str_hi", "rev_lo", "rev_hi"), self.ends),
            (("fmt_all", "fmt_n", "fmt_lo", "fmt_hi"), self.fmt), (("st_n", "st_mean", "st_m2", "st_m3", "st_m4"), self.st),
        ):
            if values is not None:
                out |= zip(names, values, strict=True)
        if self.hll is not None:
            out["hll"] = self.hll.image()
        if self.bins is not None:
            out["bins"] = [{"x": x, "y": y} for x, y in zip(*(c.tolist() for c in self.bins.settle()), strict=True)]
        return out


def _bounds(old, lo, hi):
    return (lo, hi) if old is None else (min(old[0], lo), max(old[1], hi))


def _moments(a, b):
    """Central moments (n, mean, m2, m3, m4) of two sets as one."""
    if a is None:
        return b
    (na, ma, a2, a3, a4), (nb, mb, b2, b3, b4) = a, b
    n, d = na + nb, mb - ma
    return (
        n, ma + d * nb / n, a2 + b2 + d * d * na * nb / n,
        a3 + b3 + d**3 * na * nb * (na - nb) / n**2 + 3 * d * (na * b2 - nb * a2) / n,
        a4 + b4 + d**4 * na * nb * (na * na - na * nb + nb * nb) / n**3 + 6 * d * d * (na * na * b2 + nb * nb * a2) / n**2 + 4 * d * (na * b3 - nb * a3) / n,
    )


def fold_states(docs: DataFrame, names: tuple[str, ...], equivalence: str | dict = "kind", examples: int = 100, seed: int = 0, scale: int = 0, bloom: tuple[int, float] = (1_000_000, 0.01)) -> DataFrame:
    """States of (doc_id, json): part is `node`, `keyset`, `example`, `divisor` or `bloom`. names: monoids to fold.

    equivalence: "kind", "label" or tags by (kind, sorted keys). Ids may be of any type: only their hashes, with those of
    the texts, choose examples.
    """
    ask = set(names)
    if "maxmin" in ask:
        ask |= {"maxmin_number", "maxmin_string", "maxmin_array"}
    with_keys = bool(ask & {"required", "dependencies", "attribute_counts"})
    hashed = bool(ask & {"hll", "bloom"})
    numbers, strings = hashed or bool(ask & {"maxmin_number", "stats", "multiple", "histogram"}), hashed or bool(ask & {"maxmin_string", "pattern", "format"})
    arrays = bool(ask & {"maxmin_array", "unique"})
    sampled = "examples" in ask
    blocks, hashes = bloom_size(*bloom)

    def run(batches):
        tests = [(n, re.compile(p, re.A)) for n, p in FORMATS.items()]
        places: dict = {}
        paths: list = []
        states: list[State] = []
        values: list = []  # of each place, the chunk's values, and their documents
        owners: list = []
        steps: dict = {}
        tags: dict = {}

        def place(parent, step, tag, kind):
            at = places[parent, step, tag] = len(paths)
            pp, pt = (paths[parent][0], paths[parent][1]) if parent >= 0 else ("", "")
            paths.append((pp + step, f"{pt}{step}<{tag}>", pt, step, kind, tag))
            states.append(State())
            values.append([])
            owners.append([])
            return at

        def tag_of(v):
            k = tuple(v)
            t = tags.get(k)
            if t is None:
                keys = tuple(sorted(k))
                t = tags[k] = label_tag(keys) if equivalence == "label" else equivalence[hashlib.md5("\x1f".join(keys).encode()).digest()]
                if len(tags) > FLUSH:
                    tags.clear()
            return t

        def step_of(k):
            s = steps[k] = step_text(k)
            if len(steps) > FLUSH:
                steps.clear()
            return s

        def of_numbers(s, vs):
            try:
                x = np.array(vs, np.float64)
            except OverflowError:
                x = np.array([float(v) if abs(v) < 10**300 else float("inf") * (1 if v > 0 else -1) for v in vs])
            if "maxmin_number" in ask:
                s.num = _bounds(s.num, float(x.min()), float(x.max()))
            if "stats" in ask:
                with np.errstate(all="ignore"):
                    m = x.mean()
                    d = x - m
                    d2 = d * d
                    s.st = _moments(s.st, (len(x), float(m), float(d2.sum()), float((d2 * d).sum()), float((d2 * d2).sum())))
            if "histogram" in ask:
                s.bins = s.bins or Bins()
                s.bins.add(x)
            if "multiple" in ask:
                y = x * 10.0**scale
                near = np.rint(y)
                ok = bool((np.isfinite(y) & (np.abs(near) < 2.0**63) & ((np.abs(y - near) <= 1e-9 * np.maximum(1, np.abs(y))) if scale else near == y)).all())
                g = 0
                if ok:
                    exact = near.astype(np.int64) if scale or float(np.abs(near).max()) < 2.0**53 else np.array([int(v) for v in vs], object)
                    g = int(np.gcd.reduce(np.abs(exact)))
                s.gcd = (int(np.gcd(s.gcd[0], g)), s.gcd[1] and ok) if s.gcd else (g, ok)

        def of_strings(s, vs):
            if "maxmin_string" in ask:
                n = list(map(len, vs))
                s.string = _bounds(s.string, min(n), max(n))
            if "pattern" in ask:
                r = [v[::-1] for v in vs]
                lo, hi, rlo, rhi = min(vs), max(vs), min(r), max(r)
                s.ends = (lo, hi, rlo, rhi) if s.ends is None else (min(s.ends[0], lo), max(s.ends[1], hi), min(s.ends[2], rlo), max(s.ends[3], rhi))
            if "format" in ask:
                # once values have two labels, or one has none, no merge can bring a label back: the rest isn't tested
                all_, n, lo, hi = s.fmt or (0, 0, None, None)
                if n == all_ and lo == hi:
                    for v in vs:
                        got = next((name for name, t in tests if t.search(v)), None)
                        if got is None:
                            break
                        n, lo, hi = n + 1, got if lo is None else min(lo, got), got if hi is None else max(hi, got)
                        if lo != hi:
                            break
                s.fmt = (all_ + len(vs), n, lo, hi)

        def sketch(s, vs, text):
            """Returns how many filter blocks there are now."""
            h = hash_texts(list(map(text, set(vs))))
            if "hll" in ask:
                s.hll = s.hll or Hll()
                s.hll.add(h)
            if "bloom" not in ask:
                return 0
            s.bloom = s.bloom or Bloom(blocks, hashes)
            s.bloom.add(h)
            return len(s.bloom.blocks)

        def reduce(ids):
            """Fold the chunk's values; the number of filter blocks that are held."""
            mixed = mix(ids.astype(np.uint64) ^ np.uint64(seed * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) if sampled else None
            held = 0
            for at, vs in enumerate(values):
                s, kind = states[at], paths[at][4]
                if not vs:
                    held += len(s.bloom.blocks) if s.bloom else 0
                    continue
                if kind == "number" and numbers:
                    of_numbers(s, vs)
                    if hashed:
                        held += sketch(s, vs, canonical_number)
                elif kind == "string" and strings:
                    of_strings(s, vs)
                    if hashed:
                        held += sketch(s, vs, encode_basestring)
                elif kind == "array" and arrays:
                    if "maxmin_array" in ask:
                        n = list(map(len, vs))
                        s.array = _bounds(s.array, min(n), max(n))
                    if "unique" in ask and s.uniq is not False:
                        s.uniq = all(len(v) < 2 or len({canonical(e) for e in v}) == len(v) for v in vs)
                if sampled and kind not in ("object", "array"):
                    d = np.array(owners[at], np.int64)
                    first = np.concatenate(([True], d[1:] != d[:-1]))
                    again = np.arange(len(d)) - np.maximum.accumulate(np.where(first, np.arange(len(d)), 0))
                    h = mix(mixed[d] + again.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
                    slot = (mix(h) % np.uint64(examples)).astype(np.int64)
                    order = np.lexsort((h, slot))
                    lead = order[np.concatenate(([True], slot[order][1:] != slot[order][:-1]))]
                    for i in lead.tolist():
                        k = int(h[i]) - (1 << 63)
                        old = s.slots.get(int(slot[i]))
                        if old is None or k < old[0]:
                            s.slots[int(slot[i])] = (k, canonical(vs[i]))
                values[at] = []
                owners[at] = []
            return held

        def rows():
            cols: list[list] = [[] for _ in NAMES]

            def put(part, path, **fields):
                fields |= zip(("part", "path", "typed_path", "parent_typed_path", "step", "kind", "tag"), (part, *path), strict=True)
                for name, c in zip(NAMES, cols, strict=True):
                    c.append(fields.get(name))

            def sent():
                out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, TYPES, strict=True)], NAMES)
                for c in cols:
                    c.clear()
                return out

            weight = 0
            for path, s in zip(paths, states, strict=True):
                if not s.n:
                    continue
                defaults = {"fmt_all": 0, "fmt_n": 0} if "format" in ask else {}
                put("node", path, **(defaults | ({"st_n": 0} if "stats" in ask else {}) | s.fields()))
                if with_keys and path[4] == "object":
                    merged: Counter = Counter()
                    for k, n in s.keys.items():
                        merged[tuple(sorted(k))] += n
                    for k, n in merged.items():
                        put("keyset", path, n=n, keys=list(k))
                for slot, (k, e) in s.slots.items():
                    put("example", path, slot=slot, key=k, example=e)
                if s.gcd is not None:
                    put("divisor", path, divisor=s.gcd[0], integers=s.gcd[1])
                for block, bits in (s.bloom.blocks if s.bloom else {}).items():
                    put("bloom", path, slot=block + 1, bits=bits.tobytes())
                    weight += 1
                    if weight % 2000 == 0:
                        yield sent()
                if len(cols[0]) > 10_000:
                    yield sent()
            if cols[0]:
                yield sent()
            for x in (places, paths, states, values, owners):
                x.clear()

        keysets = 0
        for b in batches:
            for at in range(0, b.num_rows, CHUNK):
                part = b.slice(at, CHUNK)
                for doc, text in enumerate(part.column(1).to_pylist()):
                    try:
                        todo = [(-1, "$", parse_strict(text))]
                    except ValueError:
                        continue
                    while todo:
                        parent, step, v = todo.pop()
                        c = v.__class__
                        if c is str:
                            kind = tag = "string"
                        elif c is dict:
                            kind = "object"
                            tag = kind if equivalence == "kind" else tag_of(v)
                        else:
                            kind = "number" if c is int or c is float else "array" if c is list else "null" if v is None else "boolean"
                            tag = kind if equivalence.__class__ is str else equivalence[kind]
                        if c is str and equivalence.__class__ is dict:
                            tag = equivalence[kind]
                        p = places.get((parent, step, tag))
                        if p is None:
                            p = place(parent, step, tag, kind)
                        s = states[p]
                        s.n += 1
                        if c is dict:
                            todo += [(p, steps.get(k) or step_of(k), x) for k, x in v.items()]
                            if with_keys:
                                k = tuple(v)
                                keysets += k not in s.keys
                                s.keys[k] += 1
                        elif c is list:
                            todo += [(p, "[*]", x) for x in v]
                            if arrays:
                                values[p].append(v)
                        elif sampled:
                            values[p].append(v)
                            owners[p].append(doc)
                        elif (strings and c is str) or (numbers and (c is int or c is float)):
                            values[p].append(v)
                held = reduce(part.column(0).to_numpy(zero_copy_only=False))
                if len(paths) > FLUSH or keysets > FLUSH or held > FLUSH_BLOCKS:
                    yield from rows()
                    keysets = 0
        if paths:
            yield from rows()

    # ids are told with their texts, so that null or repeated ids don't hide each other's values
    own = F.xxhash64("doc_id", "json") if sampled else F.lit(0).cast("long")
    return docs.select(own.alias("doc_id"), "json").mapInArrow(run, STATE)
