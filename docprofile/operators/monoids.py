"""Monoids as mergeable aggregates over the facts of one typed path.

Each monoid has a partial (aggregates of facts that make its state), a merge (aggregates of states, of the same names) and
a finish (columns read out of a merged state). All are DataFrame expressions, so one GROUP BY typed_path computes any
choice of them, with map-side partials; batch, tree and stream use the same expressions. NULL is the identity of each.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions import formats
from ..functions.texts import common_prefix
from .sketches import LG_K, shrunk

Columns = dict[str, Column]


@dataclass(frozen=True)
class Monoid:
    name: str
    #: Fact fields it reads.
    needs: tuple[str, ...]
    partial: Callable[[], Columns]
    merge: Callable[[], Columns]
    finish: Callable[[], Columns] = dict
    #: Kinds of nodes it applies to; others hold NULL.
    applies_to: tuple[str, ...] = ()


def _same(names: dict[str, Callable[[str], Column]]) -> Columns:
    return {n: f(n) for n, f in names.items()}


def count() -> Monoid:
    return Monoid("count", (), lambda: {"n": F.count(F.lit(1))}, lambda: {"n": F.sum("n")})


def maxmin(what: str) -> Monoid:
    """Bounds of numbers, of string lengths or of array lengths."""
    value = {"number": F.col("num"), "string": F.char_length("str"), "array": F.col("arr_len")}[what]
    need = {"number": "num", "string": "str", "array": "arr_len"}[what]
    lo, hi = f"{what}_min", f"{what}_max"
    return Monoid(f"maxmin_{what}", (need,), lambda: {lo: F.min(value), hi: F.max(value)}, lambda: {lo: F.min(lo), hi: F.max(hi)}, applies_to=(what,))


def unique(cap: int | None = None) -> Monoid:
    """All arrays hold distinct elements; with a cap, arrays longer than it count as not unique."""
    value = F.col("uniq") if cap is None else F.col("uniq") & (F.col("arr_len") <= cap)
    return Monoid("unique", ("uniq", "arr_len"), lambda: {"all_unique": F.bool_and(value)}, lambda: {"all_unique": F.bool_and("all_unique")}, applies_to=("array",))


def pattern() -> Monoid:
    """Common prefix and suffix: the common prefix of a set is that of its least and greatest element."""
    ends = {"str_lo": F.min, "str_hi": F.max, "rev_lo": F.min, "rev_hi": F.max}
    return Monoid(
        "pattern", ("str",),
        lambda: {"str_lo": F.min("str"), "str_hi": F.max("str"), "rev_lo": F.min(F.reverse("str")), "rev_hi": F.max(F.reverse("str"))},
        lambda: _same(ends),
        lambda: {"prefix": common_prefix(F.col("str_lo"), F.col("str_hi")), "suffix": F.reverse(common_prefix(F.col("rev_lo"), F.col("rev_hi")))},
        ("string",),
    )


def format_(engine: str = "each") -> Monoid:
    """The one format of all values. State: values, labelled values, least and greatest label; so a label isn't taken over values without one."""
    label = {"each": formats.label, "combined": formats.label_combined}[engine]
    return Monoid(
        "format", ("str",),
        lambda: {"fmt_all": F.count("str"), "fmt_n": F.count(label(F.col("str"))), "fmt_lo": F.min(label(F.col("str"))), "fmt_hi": F.max(label(F.col("str")))},
        lambda: {"fmt_all": F.sum("fmt_all"), "fmt_n": F.sum("fmt_n"), "fmt_lo": F.min("fmt_lo"), "fmt_hi": F.max("fmt_hi")},
        lambda: {"format": F.when((F.col("fmt_n") > 0) & (F.col("fmt_n") == F.col("fmt_all")) & (F.col("fmt_lo") == F.col("fmt_hi")), F.col("fmt_lo"))},
        ("string",),
    )


MOMENTS = ("st_n", "st_mean", "st_m2", "st_m3", "st_m4")


def moments_of_both(a: Column, b: Column) -> Column:
    """Count, mean and central moments of two sets as one."""
    na, nb = a["st_n"], b["st_n"].cast("double")
    n, d = na + nb, b["st_mean"] - a["st_mean"]
    d_n, ab = d / n, na * nb
    m2, m3, m4 = (a[k] + b[k] for k in MOMENTS[2:])
    both = (
        n, a["st_mean"] + d_n * nb, m2 + d * d_n * ab,
        m3 + d * d_n * d_n * ab * (na - nb) + 3 * d_n * (na * b["st_m2"] - nb * a["st_m2"]),
        m4 + d * d_n * d_n * d_n * ab * (na * na - ab + nb * nb) + 6 * d_n * d_n * (na * na * b["st_m2"] + nb * nb * a["st_m2"]) + 4 * d_n * (na * b["st_m3"] - nb * a["st_m3"]),
    )
    alone = (nb, *(b[c] for c in MOMENTS[1:]))
    return F.struct(*[F.when(na == 0, y).otherwise(x).alias(c) for c, x, y in zip(MOMENTS, both, alone, strict=True)])


def stats() -> Monoid:
    """Count, mean and central moments up to the fourth, kept as the moments themselves so that states can be merged."""
    x, n = F.col("num"), F.count("num")
    var = F.var_pop(x)

    def partial():
        return {"st_n": n, "st_mean": F.avg(x), "st_m2": var * n, "st_m3": F.coalesce(F.when(var > 0, F.skewness(x)), F.lit(0.0)) * n * F.pow(var, F.lit(1.5)), "st_m4": F.coalesce(F.when(var > 0, F.kurtosis(x) + 3), F.lit(0.0)) * n * var * var}

    def merge():
        # pairwise about the two means, so that values far from zero keep their digits
        got = F.aggregate(F.array_sort(F.collect_list(F.when(F.col("st_n") > 0, F.struct(*MOMENTS)))), F.struct(*[F.lit(0.0).alias(c) for c in MOMENTS]), moments_of_both)
        return {"st_n": F.sum("st_n")} | {c: F.when(F.sum("st_n") > 0, got[c]) for c in MOMENTS[1:]}

    def finish():
        n_, m2 = F.col("st_n"), F.col("st_m2")
        return {"mean": F.col("st_mean"), "stddev": F.sqrt(m2 / n_), "skewness": F.when(m2 > 0, F.sqrt(n_) * F.col("st_m3") / F.pow(m2, F.lit(1.5))), "kurtosis": F.when(m2 > 0, n_ * F.col("st_m4") / (m2 * m2) - 3)}

    return Monoid("stats", ("num",), partial, merge, finish, ("number",))


def hll(lg_k: int = LG_K) -> Monoid:
    """Distinct values by HyperLogLog over hashes of canonical texts, so that equal numbers count once."""
    hashed = F.when(F.col("text").isNotNull() & F.col("kind").isin("number", "string"), F.xxhash64("text"))
    return Monoid(
        "hll" if lg_k == LG_K else f"hll_{lg_k}", ("text",), lambda: {"hll": F.hll_sketch_agg(hashed, F.lit(lg_k))}, lambda: {"hll": F.hll_union_agg("hll")},
        lambda: {"distinct": F.when(F.col("kind").isin("number", "string"), F.hll_sketch_estimate("hll"))}, ("number", "string"),
    )


def histogram(bins: int = 100) -> Monoid:
    """Streaming histogram whose nearest bins are joined; states merge by the same rule."""
    return Monoid("histogram" if bins == 100 else f"histogram_{bins}", ("num",), lambda: {"bins": F.histogram_numeric("num", F.lit(bins))}, lambda: {"bins": merge_bins(F.flatten(F.collect_list("bins")), bins)}, applies_to=("number",))


def merge_bins(bins: Column, most: int) -> Column:
    """Bins of several states as at most `most` (counts added, values averaged by count), by one vectorised pass over a group's bins."""

    @F.arrow_udf("array<struct<x:double,y:double>>")
    def join(lists: pa.Array) -> pa.Array:
        ends, cols = [0], ([], [])
        flat = lists.flatten()
        x, y = (flat.field(i).to_numpy(zero_copy_only=False) for i in (0, 1))
        at = 0
        for n in pc.fill_null(pc.list_value_length(lists), 0).to_pylist():
            for c, v in zip(cols, shrunk(x[at : at + n], y[at : at + n], most), strict=True):
                c.append(v)
            at += n
            ends.append(ends[-1] + len(cols[0][-1]))
        parts = [pa.array(np.concatenate(c) if c else np.zeros(0), pa.float64()) for c in cols]
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.StructArray.from_arrays(parts, ["x", "y"]))

    got = join(bins)
    return F.when(F.count("bins") > 0, got)


#: Names by which discover() takes monoids that are columns of the profile.
REGISTRY: dict[str, Callable[[], list[Monoid]]] = {
    "maxmin_number": lambda: [maxmin("number")], "maxmin_string": lambda: [maxmin("string")], "maxmin_array": lambda: [maxmin("array")],
    "maxmin": lambda: [maxmin("number"), maxmin("string"), maxmin("array")],
    "unique": lambda: [unique()], "pattern": lambda: [pattern()], "format": lambda: [format_()], "stats": lambda: [stats()], "hll": lambda: [hll()], "histogram": lambda: [histogram()],
}
#: Those that are tables of their own, and what each reads.
SIDE = {"required": ("keys",), "dependencies": ("keys",), "attribute_counts": ("keys",), "examples": ("text",), "multiple": ("num", "whole"), "bloom": ("text",)}
PRESETS = {
    "minimum": (),
    "simple": ("dependencies", "examples", "format", "maxmin", "multiple", "pattern", "required", "unique"),
    "all": ("dependencies", "examples", "format", "maxmin", "multiple", "pattern", "required", "unique", "attribute_counts", "bloom", "histogram", "hll", "stats"),
}


def register_monoid(name: str, needs: tuple[str, ...], partial, merge, finish=dict, applies_to: tuple[str, ...] = ()) -> None:
    """A monoid of the user's own: three builders of named columns."""
    REGISTRY[name] = lambda: [Monoid(name, needs, partial, merge, finish, applies_to)]


@dataclass
class Choice:
    """Monoids of a discovery: columns and side tables."""

    names: tuple[str, ...]
    columns: list[Monoid] = field(default_factory=list)
    side: tuple[str, ...] = ()

    @property
    def needs(self) -> tuple[str, ...]:
        return tuple(sorted({n for m in self.columns for n in m.needs} | {n for s in self.side for n in SIDE[s]}))


def choose(monoids: str | list[str] | tuple[str, ...]) -> Choice:
    names = PRESETS[monoids] if isinstance(monoids, str) and monoids in PRESETS else (monoids,) if isinstance(monoids, str) else tuple(monoids)
    unknown = [n for n in names if n not in REGISTRY and n not in SIDE]
    if unknown:
        raise ValueError(f"no monoid named {', '.join(unknown)}")
    return Choice(names, [count(), *(m for n in names if n in REGISTRY for m in REGISTRY[n]())], tuple(n for n in names if n in SIDE))
