"""Discovery: documents to a profile, and the merge of profiles."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.texts import bucket
from .flatten import MAX_DEPTH, Equivalence, flatten, flatten_arrow, parse_documents, tags_of
from .fold import FOLDED, fold_states
from .monoids import Choice, choose
from .sketches import BLOCK_BITS, bloom_size

#: What tells a row of the profile, besides its typed path; functions of it, so any value of a group will do.
IDENTITY = ("path", "parent_typed_path", "step", "kind", "tag")
#: Slots of examples of a path; distinct values that a bloom filter is sized for, and its rate of false positives then.
EXAMPLES, BLOOM_EXPECTED, BLOOM_FPP = 100, 1_000_000, 0.01
#: Partitions of states whose rows of one path are merged in one go; more make another level.
LEVEL = 256


@dataclass
class Profile:
    """nodes: one row a typed path with the states of the chosen monoids; the rest are side tables keyed by typed_path."""

    nodes: DataFrame
    choice: Choice
    keysets: DataFrame | None = None
    examples: DataFrame | None = None
    divisors: DataFrame | None = None
    bloom: DataFrame | None = None
    options: dict = field(default_factory=dict)
    #: What the tables were made from, kept while they are in use.
    states: DataFrame | None = None

    def finished(self) -> DataFrame:
        """nodes with what their states say: pattern, format, mean, distinct, divisor and so on."""
        out = self.nodes
        for m in self.choice.columns:
            for name, c in m.finish().items():
                out = out.withColumn(name, c)
        if self.divisors is not None:
            out = out.join(self.divisors.select("typed_path", "divisor", "integers"), "typed_path", "left")
        return out

    def release(self) -> None:
        """Let go of the states that the tables share; they are computed anew if asked for again."""
        if self.states is not None:
            self.states.unpersist()


def facts_of(docs: DataFrame, needs: tuple[str, ...], equivalence: Equivalence = "kind", engine: str = "arrow", tuples: bool = False, max_depth: int = MAX_DEPTH) -> DataFrame:
    """Facts of (doc_id, json). engine: "arrow" (one Python pass, any depth) or "variant" (engine expressions only)."""
    if engine == "arrow" and (not callable(equivalence) or not docs.isStreaming):
        return flatten_arrow(docs, tags_of(docs, equivalence) if callable(equivalence) else equivalence, needs, tuples)
    good, _ = parse_documents(docs)
    want = tuple(n for n in needs if n != "whole")
    rows = flatten(good, equivalence, want, max_depth, tuples)
    too_deep = F.raise_error(F.lit(f"documents nest deeper than max_depth = {max_depth}: raise it, or use engine='arrow'"))
    rows = rows.withColumn("typed_path", F.when(F.col("truncated"), too_deep).otherwise(F.col("typed_path")))
    if "whole" in needs:
        rows = rows.withColumn("whole", F.when((F.col("num") == F.floor("num")) & (F.abs("num") < 2.0**63), F.col("num").cast("long")))
    return rows


def reduce_states(states: DataFrame, choice: Choice, fanin: int | None = None) -> DataFrame:
    """Merge rows of states by typed path; fanin: one more level over salted groups first, so no task merges all states of a path."""
    merged = {k: c for m in choice.columns for k, c in m.merge().items()}
    ids = [F.first(c).alias(c) for c in IDENTITY]
    if fanin:
        states = states.groupBy("typed_path", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(fanin)).alias("_salt")).agg(*ids, *[c.alias(k) for k, c in merged.items()])
    elif {m.name for m in choice.columns} & {"stats", "histogram"}:
        # these gather a path's states in one row: LEVEL partitions of them at a time
        states = states.groupBy("typed_path", _level().alias("_salt")).agg(*ids, *[c.alias(k) for k, c in merged.items()])
    return states.groupBy("typed_path").agg(*ids, *[c.alias(k) for k, c in merged.items()])


def _level() -> Column:
    return F.floor(F.spark_partition_id() / LEVEL)


def keysets_of(facts: DataFrame) -> DataFrame:
    """typed_path, keys, n: the distinct key sets of objects; all that key monoids need, whatever the number of documents."""
    return facts.where("kind = 'object'").groupBy("typed_path", "keys").agg(F.count(F.lit(1)).alias("n"))


def slots(facts: DataFrame, k: int = EXAMPLES, seed: int = 0) -> DataFrame:
    """typed_path, slot, key, example: of each slot (hash of a node) the value with the least hash. Plain aggregation: no sort, works on streams."""
    h = F.xxhash64("doc_id", "ordinal", F.lit(seed))
    return facts.where("text is not null").groupBy("typed_path", F.pmod(F.xxhash64(h), F.lit(k)).alias("slot")).agg(F.min(F.struct(h.alias("key"), F.col("text").alias("example"))).alias("e")).select("typed_path", "slot", "e.key", "e.example")


def bottom_k(facts: DataFrame, k: int = EXAMPLES, seed: int = 0, distinct: bool = False, key: Column | None = None) -> DataFrame:
    """typed_path, key, example, total: a uniform sample without replacement, the k values with the least keyed hashes.

    distinct: of distinct values. Spark keeps k a path and task before the shuffle (k up to 1000).
    """
    rows = facts.where("text is not null")
    if distinct:
        rows = rows.groupBy("typed_path", "text").agg(F.count(F.lit(1)).alias("c"))
        h = F.xxhash64("text", F.lit(seed)) if key is None else key
    else:
        h = F.xxhash64("doc_id", "ordinal", F.lit(seed)) if key is None else key
    totals = rows.groupBy("typed_path").agg(F.count(F.lit(1)).alias("total"))
    w = Window.partitionBy("typed_path").orderBy("key", "example")
    kept = rows.select("typed_path", h.alias("key"), F.col("text").alias("example")).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).drop("_r")
    return kept.join(F.broadcast(totals), "typed_path")  # schema-sized


def merge_bottom_k(a: DataFrame, b: DataFrame, k: int = EXAMPLES) -> DataFrame:
    """The k least of two samples: the sample of both inputs."""
    totals = a.select("typed_path", "total").distinct().unionByName(b.select("typed_path", "total").distinct()).groupBy("typed_path").agg(F.sum("total").alias("total"))
    w = Window.partitionBy("typed_path").orderBy("key", "example")
    both = a.drop("total").unionByName(b.drop("total")).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).drop("_r")
    return both.join(totals, "typed_path")


def merge_reservoirs(a: list, total_a: int, b: list, total_b: int, k: int, seed: int = 0) -> tuple[list, int]:
    """Two reservoirs as one, drawing each element from a reservoir with the odds of what is left of its population."""
    rng = np.random.default_rng(seed)
    a, b = list(rng.permutation(np.array(a, object))), list(rng.permutation(np.array(b, object)))
    out, left_a, left_b = [], total_a, total_b
    while len(out) < k and (a or b):
        first = bool(a) and (not b or rng.random() * (left_a + left_b) < left_a)
        out.append((a if first else b).pop())
        left_a, left_b = left_a - first, left_b - (not first)
    return out, total_a + total_b


def divisors_of(facts: DataFrame, scale: int = 0) -> DataFrame:
    """typed_path, divisor, integers: greatest common divisor of a path's numbers; null if one isn't whole (times 10^scale)."""
    return merge_divisors(divisor_rows(facts, scale))


def divisor_rows(facts: DataFrame, scale: int = 0) -> DataFrame:
    """Each Arrow batch reduced on its own, so a task sends one row a path and batch."""

    def fold(batches):
        for b in batches:
            if not b.num_rows:
                continue
            codes = b.column(0).dictionary_encode()
            num = b.column(1).to_numpy(zero_copy_only=False)
            whole = np.array([x if x is not None else 0 for x in b.column(2).to_pylist()], object) if scale == 0 else None
            at = codes.indices.to_numpy(zero_copy_only=False)
            ok = np.isfinite(num)
            if scale:
                scaled = num * 10.0**scale
                near = np.rint(scaled)
                ok &= np.abs(scaled - near) <= 1e-9 * np.maximum(1, np.abs(scaled))
                whole = np.where(np.isfinite(near) & (np.abs(near) < 2**62), near, 0).astype(np.int64)
            else:
                ok &= ~np.array([x is None for x in b.column(2).to_pylist()], bool)
                whole = np.abs(whole.astype(np.int64))
            order = np.argsort(at, kind="stable")
            first = np.flatnonzero(np.diff(at[order], prepend=-1))
            g = np.gcd.reduceat(np.abs(whole[order]), first)
            good = np.logical_and.reduceat(ok[order], first)
            yield pa.RecordBatch.from_arrays([codes.dictionary.take(pa.array(at[order][first])), pa.array(np.where(good, g, 0), pa.int64()), pa.array(good)], ["typed_path", "divisor", "integers"])

    return facts.where("kind = 'number'").select("typed_path", "num", "whole").mapInArrow(fold, "typed_path string, divisor long, integers boolean")


def gcd_of_all(rows: DataFrame, *keys: str) -> DataFrame:
    """Rows of one key as one: the common divisor of their distinct divisors."""
    gcd = F.aggregate("all", F.lit(0).cast("long"), lambda acc, x: F.aggregate(F.sequence(F.lit(1), F.lit(92)), F.struct(acc.alias("a"), x.alias("b")), lambda s, _: F.when(s["b"] == 0, s).otherwise(F.struct(s["b"].alias("a"), (s["a"] % s["b"]).alias("b"))), lambda s: s["a"]))
    return rows.groupBy(*keys).agg(F.collect_set("divisor").alias("all"), F.bool_and("integers").alias("integers")).select("typed_path", F.when(F.col("integers"), gcd).alias("divisor"), "integers")


def merge_divisors(rows: DataFrame) -> DataFrame:
    """Rows of one path as one, LEVEL partitions at a time first."""
    return gcd_of_all(gcd_of_all(rows.withColumn("_salt", _level()), "typed_path", "_salt"), "typed_path")


def bloom_positions(h: Column, size: int, places: int) -> tuple[Column, Column]:
    """Block (from 1) and places in it of a value with 64-bit hash h."""
    part = lambda shift, mask: F.shiftrightunsigned(h, shift).bitwiseAND(F.lit(mask).cast("long"))
    a, b = part(0, BLOCK_BITS - 1), part(15, BLOCK_BITS - 1).bitwiseOR(F.lit(1).cast("long"))
    return part(40, size - 1) + 1, F.array(*[(a + b * i).bitwiseAND(F.lit(BLOCK_BITS - 1).cast("long")) for i in range(places)])


def bloom_of(facts: DataFrame, expected: int = BLOOM_EXPECTED, fpp: float = BLOOM_FPP) -> DataFrame:
    """typed_path, bucket, bits: bitmap blocks of each string and number path."""
    block, places = bloom_positions(F.xxhash64("text"), *bloom_size(expected, fpp))
    rows = facts.where("kind in ('string', 'number') and text is not null").select("typed_path", block.alias("bucket"), F.explode(places).alias("p"))
    return rows.groupBy("typed_path", "bucket").agg(F.bitmap_construct_agg("p").alias("bits"))


def bloom_contains(bloom: DataFrame, values: DataFrame, expected: int = BLOOM_EXPECTED, fpp: float = BLOOM_FPP) -> DataFrame:
    """values(typed_path, text) with `member`: all bits of the value are set."""
    block, places = bloom_positions(F.xxhash64("text"), *bloom_size(expected, fpp))
    hit = values.withColumn("bucket", block).withColumn("at", places).join(bloom, ["typed_path", "bucket"], "left")
    byte = lambda p: F.conv(F.hex(F.substring(F.col("bits"), F.floor(p / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("long")
    # a number's bits as text, the last one first
    bit = lambda p: F.substring(F.reverse(F.lpad(F.bin(byte(p)), 8, "0")), (p % 8).cast("int") + 1, F.lit(1)) == "1"
    return hit.select(*values.columns, F.coalesce(F.forall("at", bit), F.lit(False)).alias("member"))


def bloom_rates(p: Profile) -> DataFrame:
    """typed_path, distinct_values, rate: the chance that a value which a path lacks passes its filter, from the bits that are set.

    A block answers for the values whose hashes lead to it, so the rate is the blocks' mean; blocks that aren't there have none."""
    size, places = bloom_size(p.options["bloom_expected"], p.options["bloom_fpp"])
    return p.bloom.groupBy("typed_path").agg((F.sum(F.pow(F.bitmap_count("bits") / BLOCK_BITS, F.lit(places))) / size).alias("rate"), (-F.sum(F.log(F.greatest(1 - F.bitmap_count("bits") / BLOCK_BITS, F.lit(1e-9)))) * BLOCK_BITS / places).alias("distinct_values"))


def sampled(docs: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """A hash filter on doc_id below the parse, so documents left out are never parsed. Any engine with md5 draws the same."""
    return docs.where(bucket(F.col("doc_id"), seed, 1_000_000) < int(fraction * 1_000_000))


def discover(docs: DataFrame, monoids="simple", equivalence: Equivalence = "kind", engine: str = "arrow", tuples: bool = False, tree_fanin: int | None = None, sample_fraction: float | None = None, seed: int = 0, max_depth: int = MAX_DEPTH, examples_engine: str = "slots", scale: int = 0, facts: DataFrame | None = None, bloom_expected: int | str = BLOOM_EXPECTED, bloom_fpp: float = BLOOM_FPP) -> Profile:
    """The profile of (doc_id, json).

    bloom_expected: distinct values of a path that membership filters are sized for; "estimate": those of the path with
    most, by a pass of HyperLogLog before. bloom_rates tells what rate a filter came to.
    """
    choice = choose(monoids)
    if sample_fraction is not None:
        docs = sampled(docs, sample_fraction, seed)
    if bloom_expected == "estimate":
        most = discover(docs, ["hll"], equivalence).finished().agg(F.max("distinct")).first()[0] if "bloom" in choice.side else None
        bloom_expected = max(1000, int(1.1 * (most or 0)))
    options = {"scale": scale, "equivalence": equivalence, "bloom_expected": bloom_expected, "bloom_fpp": bloom_fpp}
    if engine == "arrow" and not tuples and facts is None and examples_engine == "slots":
        return _folded(docs, choice, tags_of(docs, equivalence) if callable(equivalence) else equivalence, tree_fanin, seed, options)
    if engine == "arrow" and callable(equivalence) and facts is None:
        equivalence = tags_of(docs, equivalence)
    needs = tuple(sorted({*choice.needs, "arr_len"})) if tuples else choice.needs
    f = facts_of(docs, needs, equivalence, engine, tuples, max_depth) if facts is None else facts
    nodes = _nodes(f, choice, tree_fanin)
    if tuples:
        nodes = settle_tuples(nodes, f)
    p = Profile(nodes, choice, options=options)
    if set(choice.side) & KEYED:
        p.keysets = keysets_of(f)
    if "examples" in choice.side:
        p.examples = slots(f, seed=seed) if examples_engine == "slots" else bottom_k(f, seed=seed, distinct=examples_engine == "distinct")
    if "multiple" in choice.side:
        p.divisors = divisors_of(f, scale)
    if "bloom" in choice.side:
        p.bloom = bloom_of(f, bloom_expected, bloom_fpp)
    return p


KEYED = {"required", "dependencies", "attribute_counts"}


def _nodes(facts: DataFrame, choice: Choice, tree_fanin: int | None) -> DataFrame:
    ids = [F.first(c).alias(c) for c in IDENTITY]
    parts = [c.alias(k) for m in choice.columns for k, c in m.partial().items()]
    if not tree_fanin:
        return facts.groupBy("typed_path").agg(*ids, *parts)
    return reduce_states(facts.groupBy("typed_path", F.pmod(F.xxhash64("doc_id"), F.lit(tree_fanin)).alias("_salt")).agg(*ids, *parts).drop("_salt"), choice)


def _folded(docs: DataFrame, choice: Choice, equivalence: str | dict, tree_fanin: int | None, seed: int, options: dict) -> Profile:
    """The profile by the local fold; monoids that it doesn't know come from facts in one more pass."""
    own = [m for m in choice.columns if m.name in FOLDED]
    other = [m for m in choice.columns if m.name not in FOLDED]
    states = fold_states(docs, (*(m.name for m in own), *choice.side), equivalence, EXAMPLES, seed, options["scale"], (options["bloom_expected"], options["bloom_fpp"]))
    if choice.side:
        # schema-sized rows that up to five tables read: kept until release(), so that documents are parsed once
        states = states.persist(StorageLevel.MEMORY_AND_DISK)
    part = lambda name: states.where(F.col("part") == name)
    keep = [k for m in own for k in m.merge()]
    p = Profile(reduce_states(part("node").select("typed_path", *IDENTITY, *keep), Choice(choice.names, own), tree_fanin), choice, options=options, states=states if choice.side else None)
    if set(choice.side) & KEYED:
        p.keysets = part("keyset").groupBy("typed_path", "keys").agg(F.sum("n").alias("n"))
    if "examples" in choice.side:
        p.examples = part("example").groupBy("typed_path", "slot").agg(F.min(F.struct("key", "example")).alias("e")).select("typed_path", "slot", "e.key", "e.example")
    if "multiple" in choice.side:
        p.divisors = merge_divisors(part("divisor").select("typed_path", "divisor", "integers"))
    if "bloom" in choice.side:
        p.bloom = part("bloom").groupBy("typed_path", F.col("slot").alias("bucket")).agg(F.bitmap_or_agg("bits").alias("bits"))
    if other:
        f = facts_of(docs, tuple(sorted({n for m in other for n in m.needs})), equivalence)
        leaves = f if any(not m.applies_to or set(m.applies_to) & {"object", "array"} for m in other) else f.where("kind in ('number', 'string', 'boolean', 'null')")
        p.nodes = p.nodes.join(_nodes(leaves, Choice(choice.names, other), tree_fanin).drop(*IDENTITY), "typed_path", "left")
    return p


def settle_tuples(nodes: DataFrame, facts: DataFrame) -> DataFrame:
    """Arrays whose lengths were all equal (and not zero) keep their positional rows, the others their [*] rows."""
    sizes = facts.where("kind = 'array'").groupBy("typed_path").agg(F.min("arr_len").alias("_lo"), F.max("arr_len").alias("_hi"))
    fixed = [r.typed_path for r in sizes.where("_lo = _hi and _lo > 0 and _lo <= 64").collect()]  # schema-sized
    # a row goes if some step of its typed path is of the kind that its array gave up
    paths = F.array(*map(F.lit, fixed)) if fixed else F.array().cast("array<string>")
    tp = F.col("typed_path")
    star_gone = F.exists(paths, lambda a: tp.startswith(F.concat(a, F.lit("[*]"))))
    # positional steps stay only below a fixed array: every [i] in the path must follow one
    steps = F.size(F.regexp_extract_all("typed_path", F.lit(r"(\[\d+\])"), F.lit(1)))
    kept = F.aggregate(paths, F.lit(0), lambda acc, a: acc + F.when(tp.startswith(F.concat(a, F.lit("["))) & ~tp.startswith(F.concat(a, F.lit("[*]"))), 1).otherwise(0))
    return nodes.where(~star_gone & (steps == kept))


def merge_profiles(a: Profile, b: Profile) -> Profile:
    """The profile of both inputs; exact but for histograms."""
    if a.choice.names != b.choice.names:
        raise ValueError("profiles of different monoids")
    if a.bloom is not None and any(a.options.get(k) != b.options.get(k) for k in ("bloom_expected", "bloom_fpp")):
        raise ValueError("membership filters of different sizes")
    both = lambda x, y: None if x is None else x.unionByName(y)
    p = Profile(reduce_states(a.nodes.unionByName(b.nodes), a.choice), a.choice, options=a.options)
    if a.keysets is not None:
        p.keysets = both(a.keysets, b.keysets).groupBy("typed_path", "keys").agg(F.sum("n").alias("n"))
    if a.examples is not None:
        p.examples = both(a.examples, b.examples).groupBy("typed_path", "slot").agg(F.min(F.struct("key", "example")).alias("e")).select("typed_path", "slot", "e.key", "e.example") if "slot" in a.examples.columns else merge_bottom_k(a.examples, b.examples)
    if a.divisors is not None:
        rows = both(a.divisors, b.divisors)
        p.divisors = merge_divisors(rows.withColumn("divisor", F.coalesce("divisor", F.lit(0))))
    if a.bloom is not None:
        p.bloom = both(a.bloom, b.bloom).groupBy("typed_path", "bucket").agg(F.bitmap_or_agg("bits").alias("bits"))
    return p


def merge_all(profiles: list[Profile]) -> Profile:
    return reduce(merge_profiles, profiles)


def attribute_counts(keysets: DataFrame) -> DataFrame:
    """typed_path, key, n, objects, share: the union of keys, absent ones counting zero."""
    objects = keysets.groupBy("typed_path").agg(F.sum("n").alias("objects"))
    each = keysets.select("typed_path", F.explode("keys").alias("key"), "n").groupBy("typed_path", "key").agg(F.sum("n").alias("n"))
    return each.join(objects, "typed_path").withColumn("share", F.col("n") / F.col("objects"))


def required_keys(keysets: DataFrame) -> DataFrame:
    """typed_path, key: keys of every object, that is those counted as often as the object."""
    return attribute_counts(keysets).where("n = objects").select("typed_path", "key")


def cooccurrence(keysets: DataFrame) -> DataFrame:
    """typed_path, a, b, together, n_a, n_b of pairs of keys; pairs are made of distinct key sets, not of documents."""
    pairs = keysets.select("typed_path", "n", F.explode("keys").alias("a"), "keys").select("typed_path", "n", "a", F.explode("keys").alias("b")).where("a <> b")
    pairs = pairs.groupBy("typed_path", "a", "b").agg(F.sum("n").alias("together"))
    n = attribute_counts(keysets).select("typed_path", "key", "n", "objects")
    out = pairs.join(n.select("typed_path", F.col("key").alias("a"), F.col("n").alias("n_a"), "objects"), ["typed_path", "a"])
    return out.join(n.select("typed_path", F.col("key").alias("b"), F.col("n").alias("n_b")), ["typed_path", "b"])


def dependencies(keysets: DataFrame, mode: str = "directional") -> DataFrame:
    """typed_path, a, b: whenever a occurs b does (mutual: and the other way round). Pairs of keys that all objects have are left out."""
    rows = cooccurrence(keysets).where("together = n_a and n_a < objects")
    return (rows.where("n_a = n_b") if mode == "mutual" else rows).select("typed_path", "a", "b")


def attribute_groups(keysets: DataFrame) -> list[tuple[str, list[str]]]:
    """Groups of optional keys that only occur together: components over mutual pairs (schema-sized, on the driver)."""
    seen: dict = {}
    for r in dependencies(keysets, "mutual").toLocalIterator():
        a, b = seen.setdefault((r.typed_path, r.a), {r.a}), seen.setdefault((r.typed_path, r.b), {r.b})
        a |= b
        for k in a:
            seen[r.typed_path, k] = a
    return sorted({(p, tuple(sorted(g))) for (p, _), g in seen.items()})

