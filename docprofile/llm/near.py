"""Near-copy dedup: documents whose shingle sets have a Jaccard similarity of at least 0.8 are linked.

SimHash with multi-index hashing comes first: fingerprints of the same shingles within two bits are looked up by their
segments' Hamming balls, and each pair that they give is verified on the whole sets. Two texts that similar differ in some
0 to 14 of 64 bits, and balls of that radius would hold a large part of any corpus; so what the fingerprints can't reach
is found on the sets themselves, with what is linked already as a start.

A set of n shingles shares at least 4/5 of them with any set that similar, so under any common order of the shingles two
such sets have one among their first n // 5 + 1. These prefixes are the only keys; every candidate pair is verified on
the whole sets in integers, so no similar pair is missed and none is made up. The order is by hash, but shingles that
stand in more than CROWD prefixes come last: a line that many texts share is a key only of texts of little else.

A key that more than CROWD sets still share is never listed pair by pair. Sets of which too little stands in any other
crowded set to be similar to one of them leave first (partnered). Those that stay are compared with one of their key's, and
keys whose sets are then all in one component are done. The sets of the others are told by their differences from what
most of the group hold, and looked up by these, level by level (crowd_pairs); that is exact, too.

Defined cases: a shingle is five words (a text of fewer is one shingle) after bytes.lower() and bytes.split(), and is
named by its 64-bit hash; null text counts as empty; texts without words equal each other; a row is told by its id and
its text's digest, so rows that share an id (or have none) with different texts are judged apart; of a component the row
of the smallest id stays (a null id is smallest to none, ties go to the smaller digest), one of its repeated rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import delete, discard, file_system, join_unique, matched, materialise, scratch, shuffles_dropped, slices, text_digest, utf8
from .graph import components
from .simhash import links as fingerprint_links

WORDS = 5
CROWD = 32
#: Comparisons of a crowded key's sets with one of them before their differences are looked up.
ROUNDS = 1
#: How often sets that can have no partner leave the crowded keys: each time more shingles have one holder only.
LEAVE = 2


def shingles(text: bytes, size: int = WORDS, seed: int = 42) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles."""
    from xxhash import xxh64_intdigest as h

    words = text.lower().split()
    found = {h(b" ".join(words[i : i + size]), seed) for i in range(max(1, len(words) - size + 1))}
    return np.sort(np.fromiter(found, np.uint64, len(found)).view(np.int64))


def fingerprint(hashes: np.ndarray) -> int:
    """Signed fingerprint of a set of hashes: a bit is 1 if it is set in over half of them."""
    bits = np.unpackbits(hashes.astype(">i8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * bits > len(hashes)).view(">i8")[0])


def sets(docs: DataFrame, id_col: str, text_col: str, size: int) -> DataFrame:
    """uid, doc_id, digest, n, shingles, fp: one row a row of docs."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        for b in slices(batches):
            each = [shingles(t, size) for t in utf8(b.column(2))]
            ends = np.concatenate(([0], np.cumsum([len(s) for s in each]))).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(each or [np.zeros(0, np.int64)]), pa.int64()))
            fps = pa.array([fingerprint(s) for s in each], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.diff(ends), pa.int32()), lists, fps], ["doc_id", "digest", "n", "shingles", "fp"])

    rows = docs.select(F.col(id_col).alias("doc_id"), text_digest(F.col(text_col)).alias("digest"), F.col(text_col).alias("text"))
    rows = rows.mapInArrow(run, f"doc_id {kind}, digest string, n int, shingles array<long>, fp long")
    return materialise(rows.withColumn("uid", F.monotonically_increasing_id()), "sets")


def prefixes(rows: DataFrame, last: str | None = None, among_marks: tuple[str, int] | None = None) -> DataFrame:
    """uid, n, key: the first n // 5 + 1 shingles of each set; those listed at `last` come after the others. Of these keys
    only such as marks() may have met, if given."""

    def run(batches):
        common = listed(last, "key") if last else np.zeros(0, np.int64)
        met = marked(*among_marks) if among_marks else None
        for b in slices(batches):
            uids, ns, keys = [], [], []
            offsets, flat = b.column(2).offsets.to_numpy(), b.column(2).values.to_numpy()
            for uid, n, i, j in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), offsets[:-1], offsets[1:], strict=True):
                s = flat[i:j]
                if len(common):
                    late = among(common, s)
                    s = np.concatenate((s[~late], s[late]))
                s = s[: n // 5 + 1]
                s = s[met(s)] if met else s
                keys.append(s)
                uids.append(np.full(len(s), uid, np.int64))
                ns.append(np.full(len(s), n, np.int32))
            if keys:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in (uids, ns, keys)], ["uid", "n", "key"])

    return rows.select("uid", "n", "shingles").mapInArrow(run, "uid long, n int, key long")


def marks(keys: DataFrame, n: int) -> tuple[str, int]:
    """Path and log2 of the size of a bitmap in which n keys, hashes as they are, set the bit that their lowest bits name:
    some 16 bits a key, in rows of 2^15, 32 MB in all at most. It passes every key, and others too (the more, the fuller it is)."""
    size = min(28, max(15, (16 * n).bit_length()))
    place, at = F.col("key").bitwiseAND(F.lit((1 << size) - 1)), scratch(keys.sparkSession, "marks")
    with shuffles_dropped(keys.sparkSession):
        keys.groupBy(F.shiftright(place, 15).alias("block")).agg(F.bitmap_construct_agg(place.bitwiseAND(F.lit((1 << 15) - 1))).alias("bits")).write.parquet(at)
    return at, size


def marked(path: str, size: int):
    """The test of marks() for arrays of keys, as workers read it."""
    import pyarrow.dataset as ds

    fs, at = file_system(path)
    table, bits = ds.dataset(at, filesystem=fs, format="parquet").to_table(columns=["block", "bits"]), np.zeros((1 << size - 15, 1 << 12), np.uint8)
    for block, b in zip(table["block"].to_pylist(), table["bits"].to_pylist(), strict=True):
        bits[block] = np.frombuffer(b, np.uint8)

    def met(keys: np.ndarray) -> np.ndarray:
        place = keys & (1 << size) - 1
        return (bits.reshape(-1)[place >> 3] >> (place & 7).astype(np.uint8) & 1).astype(bool)

    return met


def listed(path: str, column: str) -> np.ndarray:
    """Sorted numbers of a table in the shared folder, as workers read it."""
    import pyarrow.dataset as ds

    fs, at = file_system(path)
    return np.sort(ds.dataset(at, filesystem=fs, format="parquet").to_table(columns=[column]).column(0).to_numpy())


def among(numbers: np.ndarray, values: np.ndarray) -> np.ndarray:
    return numbers[np.minimum(np.searchsorted(numbers, values), len(numbers) - 1)] == values if len(numbers) else np.zeros(len(values), bool)


def named(rows: DataFrame, uids: DataFrame) -> DataFrame:
    """uid, n, shingles of the sets that uids(u) names, as a table: only these are ever shuffled."""
    at = scratch(rows.sparkSession, "asked")
    with shuffles_dropped(rows.sparkSession):
        uids.distinct().write.parquet(at)

    def run(batches):
        asked = listed(at, "u")
        for b in batches:
            yield b.filter(pa.array(among(asked, b.column(0).to_numpy())))

    held = materialise(rows.select("uid", "n", "shingles").mapInArrow(run, "uid long, n int, shingles array<long>"), "held")
    delete(rows.sparkSession, at)
    return held


def verified(pairs: DataFrame, rows: DataFrame) -> DataFrame:
    """Those pairs (u, v) whose sets are similar."""
    if pairs.isEmpty():
        return pairs
    held = named(rows, pairs.select("u").unionByName(pairs.select(F.col("v").alias("u"))))
    # told to shuffle: the planner may take few rows of long sets for a small table
    side = lambda c: held.select(F.col("uid").alias(c), F.col("n").alias(f"n{c}"), F.col("shingles").alias(f"s{c}")).hint("merge")
    both = pairs.join(side("u"), "u").join(side("v"), "v")
    shared = F.size(F.array_intersect("su", "sv"))
    similar = materialise(both.where(9 * shared >= 4 * (F.col("nu") + F.col("nv"))).select("u", "v"), "similar")
    discard(held)
    return similar


def by_fingerprints(rows: DataFrame) -> DataFrame:
    """Edges (u, v) between similar sets that multi-index hashing of their fingerprints gives: of each fingerprint one set
    stands for all, and sets are held against that of their own and that of each fingerprint linked to it."""
    fps = materialise(rows.groupBy("fp").agg(F.min("uid").alias("first"), F.count(F.lit(1)).alias("m")), "fps")
    total = fps.agg(F.coalesce(F.sum("m"), F.lit(0))).first()[0]
    own = join_unique(rows.select("uid", "fp"), fps.where("m > 1"), ["fp"], "m", total).where("first is not null and first <> uid").select(F.col("first").alias("u"), F.col("uid").alias("v"))
    pairs = fingerprint_links(fps.select("fp"))
    side = lambda c, f: fps.select(F.col("fp").alias(f), F.col("first").alias(c)).hint("merge")
    across = pairs.select(F.col("u").alias("fu"), F.col("v").alias("fv")).join(side("a", "fu"), "fu").join(side("b", "fv"), "fv").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))
    return verified(materialise(own.unionByName(across).distinct(), "pairs"), rows)


def partnered(at: DataFrame, rows: DataFrame, rounds: int = LEAVE) -> DataFrame:
    """Those rows of at(key, uid, n) that may have a partner under their key; at's table goes. No similar pair is lost: what
    two sets share stands in both, so a set of n shingles, e of them in another set of at, is similar only to sets of at most
    (9 e - 4 n) / 4. The bitmap may count too many of them, which keeps more rows."""
    for _ in range(rounds):
        if at.isEmpty():
            break
        held = named(rows, at.select(F.col("uid").alias("u")))
        twice = materialise(held.select(F.explode("shingles").alias("key")).groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1").select("key"), "twice")
        among_marks = marks(twice, twice.count())

        def run(batches, among_marks=among_marks):
            met = marked(*among_marks)
            for b in slices(batches):
                offsets, flat = b.column(2).offsets.to_numpy(), b.column(2).values.to_numpy()
                e = np.concatenate(([0], np.cumsum(met(flat[offsets[0] : offsets[-1]]))))[offsets - offsets[0]]
                most = (9 * np.diff(e) - 4 * b.column(1).to_numpy()) // 4
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(most, pa.int64())], ["uid", "most"])

        most = materialise(held.mapInArrow(run, "uid long, most long"), "most")
        near = materialise(at.join(most.hint("merge"), "uid"), "near")
        size = near.groupBy("key").agg(F.count(F.lit(1)).alias("m"), F.min("n").alias("low"), F.max("most").alias("high"))
        stay = join_unique(near, size, ["key"], "m", near.count()).where("low <= most and n <= high").select("key", "uid", "n")
        past, at = at, materialise(stay, "crowds")
        discard(past, held, twice, most, near)
        delete(rows.sparkSession, among_marks[0])
    return at


def outermost(at: DataFrame) -> DataFrame:
    """Rows of those keys that aren't wholly inside the group of one other key: a key is left out if all its sets have
    one and the same least key, for that one's group holds each of its pairs."""
    least = at.groupBy("uid").agg(F.min("key").alias("least"))
    keys = at.select("key", "uid").join(least.hint("merge"), "uid").groupBy("key").agg(F.min("least").alias("low"), F.max("least").alias("high"))
    return at.join(keys.where("low < high or low = key").select("key").hint("merge"), "key", "left_semi")


def gathered(at: DataFrame) -> DataFrame:
    """Rows of at(key, uid, n, root) under fewer keys: each key's group goes whole into that of the key which is the most
    frequent one in most of its sets, so the many keys of one family of texts become few groups."""
    often = at.groupBy("key").agg(F.count(F.lit(1)).alias("m"))
    order = F.struct(F.col("m").alias("m"), F.col("key").alias("key"))
    ranked = materialise(join_unique(at, often.withColumn("c", F.col("m")), ["key"], "m", at.count()).withColumnRenamed("c", "m"), "ranked")
    lead = ranked.groupBy("uid").agg(F.max(order).alias("lead")).select("uid", F.col("lead.key").alias("lead"))
    votes = ranked.select("key", "uid").join(lead.hint("merge"), "uid").groupBy("key", "lead").agg(F.count(F.lit(1)).alias("c"))
    to = votes.groupBy("key").agg(F.sum("c").alias("m"), F.max(F.struct("c", "lead")).alias("most")).select("key", "m", F.col("most.lead").alias("to"))
    moved = join_unique(at, materialise(to, "leaders"), ["key"], "m", at.count())
    return moved.select(F.col("to").alias("key"), "uid", "n", "root").distinct()


def crowd_pairs(left: DataFrame, rows: DataFrame, crowd: int) -> DataFrame:
    """Pairs (u, v) that hold a path between any two similar sets of one key of left(key, uid, n, root), unless they are
    of one root already; a group's pairs are never listed.

    Sets of one key are told by how they differ from the group's core, the shingles that over half of them hold. Two sets
    differ from each other by no more than both do from the core, so sets near it are linked by way of the one nearest,
    and count as of its root. Most of a group then have one root, its main one, and only pairs with a set outside of it are
    open. Such sets share some of these differences: a prefix filter on the differences gives new keys, with fewer keys
    for sets of the main root, since they are to meet none of their own. Groups with up to `crowd` sets outside their main
    root list these against all, at most `crowd` rows a set; others go the same way again.
    """
    total = lambda df: df.agg(F.coalesce(F.sum("m"), F.lit(0))).first()[0]
    groups = materialise(gathered(left), "groups")
    held = named(rows, groups.select(F.col("uid").alias("u")))
    at, found, past = groups.join(held.select("uid", F.col("shingles").alias("d")).hint("merge"), "uid"), None, [groups, held]
    while True:
        at = materialise(at.select("key", "uid", "n", "root", "d"), "crowd")
        discard(*past)
        if at.isEmpty():
            discard(at)
            break
        size = at.groupBy("key").agg(F.count(F.lit(1)).alias("m"))
        held = at.select("key", F.explode("d").alias("e")).groupBy("key", "e").agg(F.count(F.lit(1)).alias("c"))
        core = held.join(size.hint("merge"), "key").where(2 * F.col("c") > F.col("m")).groupBy("key").agg(F.collect_list("e").alias("core"))
        core = materialise(size.join(core.hint("merge"), "key", "left"), "core")
        past = [at, core]
        core = core.withColumn("core", F.coalesce("core", F.array().cast("array<long>")))
        apart = join_unique(at, core, ["key"], "m", total(core)).withColumn("d", F.concat(F.array_except("d", "core"), F.array_except("core", "d")))
        apart = materialise(apart.select("key", "uid", "n", "root", "d", (9 * F.size("d") - F.col("n")).alias("far")), "apart")
        past.append(apart)
        best = materialise(apart.groupBy("key").agg(F.count(F.lit(1)).alias("m"), F.min(F.struct("far", "uid", "root")).alias("best")), "best")
        past.append(best)
        apart = join_unique(apart, best, ["key"], "m", total(best))
        sum_ = F.col("far") + F.col("best.far")
        star = apart.where((sum_ <= 0) & (F.col("root") != F.col("best.root"))).select(F.least("uid", "best.uid").alias("u"), F.greatest("uid", "best.uid").alias("v"))
        rooted = materialise(apart.select("key", "uid", "n", F.when(sum_ <= 0, F.col("best.root")).otherwise(F.col("root")).alias("root"), "d", "far"), "rooted")
        size = materialise(main_roots(rooted, "key"), "mains")
        past += [rooted, size]
        each = materialise(join_unique(rooted, size, ["key"], "m", total(size)).where("outside > 0"), "split")
        past.append(each)
        inside = F.col("root") == F.col("main")
        least = lambda who: F.min(F.when(who, F.col("far")))
        least = materialise(each.groupBy("key").agg(F.count(F.lit(1)).alias("m"), least(F.lit(True)).alias("all"), least(~inside).alias("out")), "least")
        past.append(least)
        # two similar sets have at least (far + far') / 18 differences in common, and one of them is outside of the main root
        sum_ = F.col("far") + F.when(inside, F.col("out")).otherwise(F.col("all"))
        each = join_unique(each, least, ["key"], "m", total(least))
        each = each.select("key", "uid", "n", "root", "far", F.greatest(F.lit(1), F.ceil(sum_ / 18)).cast("int").alias("need"), F.explode("d").alias("e"))
        often = each.groupBy("key", "e").agg(F.count(F.lit(1)).alias("f")).where("f > 1")
        # differences that one set has alone come first in the common order and make no key
        each = each.join(often.hint("merge"), ["key", "e"]).groupBy("key", "uid", "n", "root", "far", "need").agg(F.array_sort(F.collect_list(F.struct("f", "e"))).alias("all"))
        each = each.where("size(all) >= need").select("key", "uid", "n", "root", "far", "need", F.explode(F.expr("slice(all, 1, size(all) - need + 1)")).alias("x"))
        subs = materialise(each.select("key", F.xxhash64("key", "x.e").alias("sub"), "uid", "n", "root", "far", "need"), "subs")
        past.append(subs)
        size = materialise(main_roots(subs, "sub").where("outside > 0").select("sub", "m", "main", (F.col("outside") > crowd).alias("many")), "sizes")
        subs = materialise(join_unique(subs, size, ["sub"], "m", total(size)).where("many is not null"), "open")
        past += [size, subs]
        row = F.struct("uid", "n", "root", "far", "need")
        some = subs.where("not many")
        out = some.where("root <> main").groupBy("sub").agg(F.collect_list(row).alias("out"))
        out = materialise(out.join(size.select("sub", "m").hint("merge"), "sub"), "outside")
        past.append(out)
        few = join_unique(some.select("key", "sub", row.alias("a"), (F.col("root") == F.col("main")).alias("main")), out, ["sub"], "m", total(out)).select("key", "a", "main", F.explode("out").alias("b"))
        few = few.where((F.col("main") | (F.col("a.uid") < F.col("b.uid"))) & (F.col("a.root") != F.col("b.root")) & close(F.col("a.n"), F.col("b.n")))
        # up to where the first prefix of the two ends they have these c in common; beyond it at most what that set has left.
        # Pairs that also share a key of many are met there, whatever c is here
        few = few.groupBy("key", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.count(F.lit(1)).alias("c"))
        few = few.where(18 * (F.col("c") + F.greatest("a.need", "b.need") - 1) >= F.col("a.far") + F.col("b.far"))
        pairs = star.unionByName(few.select(F.col("a.uid").alias("u"), F.col("b.uid").alias("v"))).distinct()
        pairs = materialise(pairs, "found")
        found = pairs if found is None else found.unionByName(pairs)
        again = outermost(subs.where("many").select(F.col("sub").alias("key"), "uid", "n", "root", F.col("key").alias("of")))
        at = again.join(rooted.select(F.col("key").alias("of"), "uid", "d").hint("merge"), ["of", "uid"])
    return found.distinct() if found is not None else rows.sparkSession.createDataFrame([], "u long, v long")


def main_roots(at: DataFrame, key: str) -> DataFrame:
    """key, m, main, outside: of each group of at(key, root) its rows, the root of most of them and the number of the others."""
    by = at.groupBy(key, "root").agg(F.count(F.lit(1)).alias("c"))
    most = by.groupBy(key).agg(F.sum("c").alias("m"), F.max(F.struct("c", "root")).alias("most"))
    return most.select(key, "m", F.col("most.root").alias("main"), (F.col("m") - F.col("most.c")).alias("outside"))


def close(a, b):
    """Sizes of sets that may be similar."""
    return (5 * a >= 4 * b) & (5 * b >= 4 * a)


def links(rows: DataFrame, crowd: int = CROWD, rounds: int = ROUNDS) -> DataFrame:
    """Edges (u, v) between similar sets whose components are those of all similar pairs."""
    first = by_fingerprints(rows)
    at = scratch(rows.sparkSession, "common")
    with shuffles_dropped(rows.sparkSession):
        prefixes(rows).groupBy("key").agg(F.count(F.lit(1)).alias("m")).where(F.col("m") > crowd).select("key").write.parquet(at)
    size = materialise(prefixes(rows, at).groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1").withColumn("many", F.col("m") > crowd), "keys")
    total = size.agg(F.coalesce(F.sum("m"), F.lit(0))).first()[0]
    # most keys stand in one prefix: what the bitmap tells apart of these isn't written or shuffled
    met = marks(size.select("key"), size.count())
    shared = materialise(join_unique(prefixes(rows, at, met), size, ["key"], "m", total).where("many is not null"), "shared")
    delete(rows.sparkSession, at)
    delete(rows.sparkSession, met[0])
    discard(size)
    few = shared.where("not many").groupBy("key").agg(F.array_sort(F.collect_list(F.struct("uid", "n"))).alias("all"))
    few = few.select(F.explode("all").alias("a"), "all").select("a", F.explode("all").alias("b")).where((F.col("a.uid") < F.col("b.uid")) & close(F.col("a.n"), F.col("b.n")))
    few = few.groupBy(F.col("a.uid").alias("u"), F.col("b.uid").alias("v"), F.col("a.n").alias("nu"), F.col("b.n").alias("nv")).agg(F.count(F.lit(1)).alias("c"))
    # up to where the first prefix of the two ends they share these c; beyond it at most what that set has left. Pairs
    # that also share a crowded key are met there, whatever c is here
    left_of = lambda n: F.col(n) - F.floor(F.col(n) / 5) - 1
    few = few.where(9 * (F.col("c") + F.greatest(left_of("nu"), left_of("nv"))) >= 4 * (F.col("nu") + F.col("nv")))
    pairs = materialise(few.select("u", "v").join(first.hint("merge"), ["u", "v"], "left_anti"), "pairs")
    crowded = materialise(shared.where("many").select("key", "uid", "n"), "crowds")
    discard(shared)
    crowded = partnered(crowded, rows)
    edges = materialise(verified(pairs, rows).unionByName(first), "edges")
    if crowded.isEmpty():
        return edges

    def open_(edges):
        """Rows of crowded keys that hold more than one component, each with its component."""
        roots = components(edges).select(F.col("node").alias("uid"), "root")
        at = crowded.join(roots.hint("merge"), "uid", "left").select("key", "uid", "n", F.coalesce("root", "uid").alias("root"))
        at = materialise(at, "crowded")
        parts = at.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low < high").select("key")
        return materialise(at.join(parts.hint("merge"), "key"), "open")

    left = open_(edges)
    for k in range(rounds):
        if left.isEmpty():
            return edges
        # the next in an order of this round's own
        one = left.groupBy("key").agg(F.min(F.struct(F.xxhash64("uid", F.lit(k)).alias("o"), "uid", "n", "root")).alias("r"))
        pairs = left.join(one.hint("merge"), "key").where((F.col("root") != F.col("r.root")) & close(F.col("n"), F.col("r.n")))
        pairs = materialise(pairs.select(F.least("uid", "r.uid").alias("u"), F.greatest("uid", "r.uid").alias("v")).distinct(), "pairs")
        edges = materialise(edges.unionByName(verified(pairs, rows)), "edges")
        left = open_(edges)
    return materialise(edges.unionByName(verified(materialise(crowd_pairs(left, rows, crowd), "pairs"), rows)), "edges")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = WORDS, crowd: int = CROWD, rounds: int = ROUNDS) -> DataFrame:
    """docs with one row of each component, that of the smallest id; all columns stay."""
    rows = sets(docs, id_col, text_col, size)
    roots = components(links(rows, crowd, rounds)).select(F.col("node").alias("uid"), "root")
    # equal rows (same id and text) have equal sets, so they are in one component
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "digest", "uid")
    tied = rows.select("uid", "doc_id", "digest").join(roots.hint("merge"), "uid")
    gone = tied.join(tied.groupBy("root").agg(F.min(first).alias("best")).hint("merge"), "root").where("uid <> best.uid")
    gone = materialise(gone.select("uid", "doc_id", "digest"), "gone")
    # of a row that goes in part, one of its repeated rows stays
    per = rows.select("uid", "doc_id", "digest").join(gone.select("uid", F.lit(1).alias("g")).hint("merge"), "uid", "left")
    kept = per.groupBy(F.col("doc_id").alias("_id"), F.col("digest").alias("_d")).agg(F.count(F.lit(1)).alias("_m"), F.count("g").alias("_g")).where("_g < _m")
    kept = materialise(kept, "kept")
    discard(rows, gone)
    hit = docs.withColumn("_t", text_digest(F.col(text_col))).join(kept.hint("shuffle_hash"), matched([F.col(id_col), F.col("_t")], [F.col("_id"), F.col("_d")]))
    return hit.where("_m = 1").unionByName(hit.where("_m > 1").dropDuplicates([id_col, "_t"])).select(*docs.columns)
