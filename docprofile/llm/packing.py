"""Best-fit packing of tokenised documents by hierarchical residual packing.

Documents become pieces of at most `room` tokens. Each partition packs its pieces best-fit decreasing; bins with at most
`slack` tokens free are emitted, the others go on as items to the next round, over a `fan`-th of the partitions, and are
packed again, until one partition (or as many as hold `most` items each) is left, whose bins are all emitted.

Defined cases: null text counts as empty; every document ends with one more id, so none has zero pieces; repeated rows
are packed each on its own; documents longer than `room` are cut into pieces of `room` tokens; an empty table gives no
row; other columns are ignored; a null id stays null.
"""

from __future__ import annotations

import array
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Memo, materialise, slices, tokenizer_path, utf8

MEMBER = "struct<doc_id:{kind},piece:int,start:bigint,length:bigint,ids_crc32:bigint>"
#: Marks at a word's end that the pre-tokeniser parts from its letters.
MARKS = b".,;:!?*#%$&|"


#: Texts that tell whether a tokenizers file does what WordTokens takes for granted.
PROBES = ("Hello, World! it's", "ABC abc AbC.", " two  blanks\n\nand\ttabs ", "a|b x* 50% #tag &c $9.99 (x)", "É é ß Σς İ.", "don't 12,345.67 A1b2", "日本語。текст, слово!", "x" * 300, "")


class WordTokens:
    """Ids by a tokenizers file whose normaliser and pre-tokeniser never look past white space: words are encoded once.

    A word of letters with marks behind is two pieces to the pre-tokeniser, so it is put together from both. Small ASCII
    letters are what the normaliser and the byte mapping leave as they are: such a piece goes to the merges directly. A file
    that works otherwise is refused when it is loaded.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.memo, self.merge = Memo(self.word, 250_000), self.tok.model.tokenize
        for probe in PROBES:
            if self.encode(probe.encode()) != array.array("I", self.tok.encode(probe, add_special_tokens=False).ids).tobytes():
                raise ValueError(f"{path} isn't a tokenizer whose words can be encoded one by one: it differs on {probe!r}")
        self.memo.clear()

    def word(self, word: bytes) -> bytes:
        stem = word.rstrip(MARKS)
        if stem.isalpha():  # of bytes: ASCII letters only
            if len(stem) < len(word):
                return self.memo[stem.lower()] + self.memo[word[len(stem) :]]
            if not stem.islower():
                return self.memo[stem.lower()]
            return array.array("I", [t.id for t in self.merge(stem.decode())]).tobytes()
        if stem and len(stem) < len(word):
            text = stem.decode()
            # letters only, in small letters too: then no piece spans the place before the marks
            if text.isalpha() and text.lower().isalpha():
                return self.memo[stem] + self.memo[word[len(stem) :]]
        return array.array("I", self.tok.encode(word.decode(), add_special_tokens=False).ids).tobytes()

    def encode(self, text: bytes) -> bytes:
        # bytes.split() cuts at ASCII white space only, which every part of the tokenizer takes for white space
        return b"".join(map(self.memo.__getitem__, text.split()))


_OPEN: dict[str, WordTokens] = {}


def word_tokens(path: str) -> WordTokens:
    """This process's encoder: it serves all tasks that a worker runs."""
    return _OPEN.get(path) or _OPEN.setdefault(path, WordTokens(path))


def pieces(docs: DataFrame, file: str, room: int, end: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        words, tail = word_tokens(tokenizer_path(file)), end.to_bytes(4, "little")
        for b in slices(batches):
            rows = []
            for d, t in zip(b.column(0).to_pylist(), utf8(b.column(1)), strict=True):
                ids = words.encode(t) + tail
                rows += [(d, i, i * room, len(p) // 4, zlib.crc32(p)) for i in range(-(-len(ids) // (4 * room))) for p in (ids[4 * room * i : 4 * room * (i + 1)],)]
            cols = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (b.column(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


def best_fit(sizes: list[int], room: int) -> list[list[int]]:
    """Bins (lists of positions) by best fit, largest first: `open_` has a bit for each free size that some bin has."""
    bins, by_free, open_ = [], [[] for _ in range(room + 1)], 0
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        fits = open_ >> sizes[i]
        if fits:
            free = sizes[i] + ((fits & -fits).bit_length() - 1)
            at = by_free[free].pop()
            if not by_free[free]:
                open_ &= ~(1 << free)
            bins[at].append(i)
        else:
            at, free = len(bins), room
            bins.append([i])
        left = free - sizes[i]
        by_free[left].append(at)
        open_ |= 1 << left
    return bins


def _flat(joined: pa.ListArray) -> dict:
    """Columns of the members of a list array."""
    return dict(zip((f.name for f in joined.type.value_type), joined.flatten().flatten(), strict=True))


def pack(items: DataFrame, room: int = 4096, slack: int = 8, fan: int = 8, first: int = 20_000, most: int = 200_000) -> DataFrame:
    """Pieces (doc_id, piece, start, length, ids_crc32) with sequence_id and offset.

    Each bin is a row that carries its pieces, at most `room` of them. first: items of a partition in the first round;
    most: items that one task packs at most, in any round.
    """
    names = ["doc_id", "piece", "start", "length", "ids_crc32"]
    kind = MEMBER.format(kind=dict(items.dtypes)["doc_id"])
    items = materialise(items, "pieces")
    full = items.where(F.col("length") >= room).select(*names, (-F.monotonically_increasing_id() - 1).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    rows = items.where(F.col("length") < room).select(F.col("length").alias("size"), F.array(F.struct(*names)).alias("members"), F.xxhash64("doc_id", "piece").alias("_h"))
    n, rounds, packed = rows.count(), 0, []
    parts = max(1, -(-n // first))
    while True:
        last = parts == 1 or (rounds > 0 and parts <= -(-n // most))

        def run(batches, last=last, rounds=rounds):
            held = [b for b in batches if b.num_rows]
            if not held:
                return
            sizes, hashes = ([x for b in held for x in b.column(i).to_pylist()] for i in (0, 2))
            members, task = pa.concat_arrays([b.column(1) for b in held]), TaskContext.get().partitionId()
            # in an order of the items' own, so that a retried task makes the same bins
            order = sorted(range(len(sizes)), key=hashes.__getitem__)
            bins = [[order[i] for i in b] for b in best_fit([sizes[i] for i in order], room)]
            for at in range(0, len(bins), 2000):
                part = bins[at : at + 2000]
                taken = members.take(pa.array([i for b in part for i in b], pa.int64()))
                ends, offsets, k = taken.offsets.to_pylist(), [0], 0
                for b in part:
                    k += len(b)
                    offsets.append(ends[k] - ends[0])
                size = [sum(sizes[i] for i in b) for b in part]
                ids = [rounds << 56 | task << 32 | at + j if last or s >= room - slack else None for j, s in enumerate(size)]
                yield pa.RecordBatch.from_arrays([pa.array(size, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), taken.flatten()), pa.array(ids, pa.int64())], ["size", "members", "sequence_id"])

        dealt = rows.repartition(parts, "_h") if parts > 1 else rows.coalesce(1)
        made = materialise(dealt.mapInArrow(run, f"size long, members array<{kind}>, sequence_id long"), "bins")
        packed.append(made.where("sequence_id is not null"))
        if last:
            break
        rows = made.where("sequence_id is null").select("size", "members", F.xxhash64(F.col("members")[0]["doc_id"], F.col("members")[0]["piece"], F.lit(rounds)).alias("_h"))
        n, rounds = rows.count(), rounds + 1
        parts = max(1, parts // fan, -(-n // most))

    def laid(batches):
        for b in batches:
            if not b.num_rows:
                continue
            counts, flat = np.diff(b.column(0).offsets.to_numpy()), _flat(b.column(0))
            lengths = flat["length"].to_numpy()
            ends = np.cumsum(lengths)
            starts = ends - lengths
            firsts = np.concatenate(([0], np.cumsum(counts)[:-1]))
            cols = [flat[c] for c in names] + [pa.array(np.repeat(b.column(1).to_numpy(), counts)), pa.array(starts - np.repeat(starts[firsts], counts))]
            yield pa.RecordBatch.from_arrays(cols, [*names, "sequence_id", "offset"])

    bins = packed[0]
    for d in packed[1:]:
        bins = bins.unionByName(d)
    return full.unionByName(bins.select("members", "sequence_id").mapInArrow(laid, full.schema))


def pack_documents(docs: DataFrame, file: str = "word_bpe_49k.json", room: int = 4096, end: int = 1, id_col: str = "doc_id", text_col: str = "text", **kind) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row a piece."""
    return pack(pieces(docs, file, room, end, id_col, text_col), room, **kind)
