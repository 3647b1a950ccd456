"""Secret scans with corpus-wide ownership frequency. DataFrame functions only.

Base candidates are what three fixed patterns match. Further candidates are long mixed runs of credential letters that
hold upper and lower case letters and digits, or that carry a known credential prefix. Every candidate value is hashed
and the distinct repositories and owners that hold it are counted over the whole corpus: a value that many owners have, or
that more than one owner has in many repositories, is a copied example; one that a single owner has, in however many
repositories, or that few places have, looks live. Live further candidates are added as spans of kind `owned`; base spans
always stay, and the counts tell how many of a document's candidates are live and how widely its widest one is spread.

Positions come from splitting a text at its matches: lengths of what lies between and of the matches add up to code
point offsets, with no code outside the engine. Running sums and maxima go by blocks of the square root of their number,
and replaced texts by pieces, so texts with very many matches take little more than their length.

Defined cases: null text counts as empty and has no spans; repeated rows each get a row and count once for their owner;
a null owner or repository is one of its own; other columns are ignored; an empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import join_unique, matched, materialise, text_digest

# The patterns, in the order in which kinds are listed, and the least lengths.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
#: A run of these letters is matched whole or not at all, so its least length can stand in the pattern.
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}"
KINDS = ("assign", "access", "hex", "owned")
#: Further candidates: runs of credential letters; what they must hold is tested on each run.
LONG = r"[A-Za-z0-9_+/-]{20,}"
PREFIX = r"^(gh[pousr]_|sk-|xox[abpr]-|AIza|eyJ|glpat-)"
#: A value that more owners than this hold is a copied example, as is one that owners share in more repositories than this.
EXAMPLE_OWNERS, EXAMPLE_REPOS = 2, 4
#: Code points of the pieces in which a text's secrets are replaced.
PIECE = 4096


def let(value: Column, then) -> Column:
    """then(value) with value computed once: a lambda's variable isn't computed again where it is used."""
    return F.get(F.transform(F.array(value), then), 0)


def running(values: Column, both) -> Column:
    """values with each replaced by `both` of all up to it: inside blocks first, then with what the blocks before came to."""
    def plain(v):
        return F.aggregate(v, F.array().cast("array<int>"), lambda acc, x: F.array_append(acc, F.when(F.size(acc) > 0, both(F.element_at(acc, -1), x)).otherwise(x)))

    def cut(v):
        size = F.greatest(F.lit(1), F.ceil(F.sqrt(F.size(v).cast("double"))).cast("int"))
        return let(size, lambda n: F.transform(F.sequence(F.lit(0), F.floor((F.size(v) - 1) / n).cast("int")), lambda i: plain(F.slice(v, i * n + 1, n))))

    def joined(blocks):
        ends = plain(F.transform(blocks, lambda b: F.element_at(b, -1)))
        return let(ends, lambda e: F.flatten(F.transform(blocks, lambda b, i: F.when(i == 0, b).otherwise(let(F.element_at(e, F.greatest(i, F.lit(1))), lambda c: F.transform(b, lambda x: both(c, x)))))))

    return let(values, lambda v: F.when(F.size(v) > 0, let(cut(v), joined)).otherwise(F.array().cast("array<int>")))


def _places(kind: int, pattern: str, found: Column, values: Column, text: Column) -> Column:
    """array<struct<start, kind, end, value>>: running sums of the lengths between the matches and of the matches."""
    gaps = F.transform(F.split(text, pattern, -1), F.char_length)
    lengths = F.transform(found, F.char_length)
    steps = F.zip_with(F.slice(gaps, F.lit(1), F.size(found)), lengths, lambda g, m: g + m)
    ends = running(steps, lambda a, b: a + b)
    return F.zip_with(F.zip_with(ends, lengths, lambda e, n: F.struct((e - n).alias("a"), e.alias("b"))), values, lambda p, v: F.struct(p["a"].alias("start"), F.lit(kind).alias("kind"), p["b"].alias("end"), v.alias("value")))


def _outside(spans: Column) -> Column:
    """Spans in order, without those further candidates that a base match covers; they count as that only."""
    reach = running(F.transform(spans, lambda s: F.when(s["kind"] < 3, s["end"]).otherwise(F.lit(0))), F.greatest)
    paired = F.zip_with(spans, reach, lambda s, r: F.struct(s.alias("s"), r.alias("r")))
    return F.transform(F.filter(paired, lambda p: (p["s"]["kind"] < 3) | (p["r"] < p["s"]["end"])), lambda p: p["s"])


def _mixed(v: Column) -> Column:
    return v.rlike(PREFIX) | (v.rlike("[A-Z]") & v.rlike("[a-z]") & v.rlike("[0-9]"))


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source", repo_cols: tuple[str, ...] = ("source", "lang"), digest: bool = False) -> DataFrame:
    """uid, doc_id, owner, repo, spans array<struct<start, kind, end, value>>: all base matches kept, and the further candidates; on demand the text's digest."""
    none = F.array().cast("array<string>")
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(owner_col).cast("string").alias("owner"), F.to_json(F.struct(*[F.col(c).cast("string").alias(f"c{i}") for i, c in enumerate(repo_cols)])).alias("repo"), text.alias("text"))
    pick = lambda pattern: F.regexp_extract_all("text", F.lit(pattern), F.lit(0))
    rows = rows.select("*", pick(ASSIGN).alias("f0"), pick(ACCESS).alias("f1"), pick(HEX).alias("f2"), pick(LONG).alias("f3"))
    at = lambda k, pattern, keep, values=None: F.when(F.size(f"f{k}") > 0, F.filter(_places(k, pattern, F.col(f"f{k}"), F.col(f"f{k}") if values is None else values, F.col("text")), keep)).otherwise(F.array())
    yes = lambda s: F.lit(True)
    secret = F.transform("f0", lambda m: F.regexp_extract(m, ASSIGN, 2))
    owned = F.when(F.exists("f3", _mixed), at(3, LONG, lambda s: _mixed(s["value"]))).otherwise(F.array())
    spans = F.concat(at(0, ASSIGN, lambda s: F.char_length(s["value"]) >= 12, secret), at(1, ACCESS, yes), at(2, HEX, yes), owned)
    row = ["doc_id", "owner", "repo"] + (["digest"] if digest else [])
    rows = (rows.withColumn("digest", text_digest(F.col("text"))) if digest else rows).select(*row, spans.alias("spans"))
    rows = rows.select(*row, F.array_sort("spans").alias("spans"))
    rows = rows.select(*row, F.when(F.exists("spans", lambda s: s["kind"] == 3), _outside(F.col("spans"))).otherwise(F.col("spans")).alias("spans"))
    return materialise(rows.withColumn("uid", F.monotonically_increasing_id()), "candidates")


def ownership(found: DataFrame, example_owners: int = EXAMPLE_OWNERS, example_repos: int = EXAMPLE_REPOS) -> DataFrame:
    """hash, n (rows that hold it), repos, owners, live: one row a distinct candidate value of the corpus."""
    each = found.select("owner", "repo", F.explode("spans").alias("s")).select("owner", "repo", F.sha2("s.value", 256).alias("hash"))
    places = each.groupBy("hash", "owner", "repo").agg(F.count(F.lit(1)).alias("n"))
    by_owner = places.groupBy("hash", "owner").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("repos"))
    return by_owner.groupBy("hash").agg(F.sum("n").alias("n"), F.sum("repos").alias("repos"), F.count(F.lit(1)).alias("owners")).withColumn("live", (F.col("owners") == 1) | ((F.col("owners") <= example_owners) & (F.col("repos") <= example_repos)))


def judged(found: DataFrame, example_owners: int = EXAMPLE_OWNERS, example_repos: int = EXAMPLE_REPOS) -> DataFrame:
    """found with each span's `live`, owners and repositories, and without further candidates that aren't live."""
    values = materialise(ownership(found, example_owners, example_repos), "owners")
    total = values.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    each = found.select("uid", F.explode("spans").alias("s")).select("uid", "s.start", "s.kind", "s.end", F.sha2("s.value", 256).alias("hash"))
    each = join_unique(each, values, ["hash"], "n", total).where("kind < 3 or live")
    mine = each.groupBy("uid").agg(F.array_sort(F.collect_list(F.struct("start", "kind", "end", "live", "owners", "repos"))).alias("judged"))
    return found.drop("spans").join(mine, "uid", "left").withColumn("judged", F.coalesce("judged", F.array().cast("array<struct<start:int,kind:int,end:int,live:boolean,owners:bigint,repos:bigint>>")))


def _text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(F.array(*map(F.lit, KINDS)), s["kind"] + 1), s["start"], s["end"])), ",")


def scan(docs: DataFrame, example_owners: int = EXAMPLE_OWNERS, example_repos: int = EXAMPLE_REPOS, **cols) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_example, most_owners, most_repos: one row a row of docs."""
    rows = judged(candidates(docs, **cols), example_owners, example_repos)
    count = lambda cond: F.size(F.filter("judged", cond)).cast("long")
    of = lambda k: count(lambda s: s["kind"] == k)
    widest = lambda c: F.coalesce(F.array_max(F.transform("judged", lambda s: s[c])), F.lit(0).cast("long")).alias(f"most_{c}")
    return rows.select("doc_id", *[of(k).alias(f"n_{KINDS[k]}") for k in range(3)], F.sha2(_text(F.filter("judged", lambda s: s["kind"] < 3)).cast("binary"), 256).alias("base_sha256"), _text(F.col("judged")).alias("spans"), count(lambda s: s["live"]).alias("n_live"), count(lambda s: ~s["live"]).alias("n_example"), widest("owners"), widest("repos"))


def redact(docs: DataFrame, mark: str = "[SECRET]", id_col: str = "doc_id", text_col: str = "text", **cols) -> DataFrame:
    """docs with each live span replaced by `mark` (overlapping ones by one); no row goes, all columns stay."""
    # spans are those of the text alone: rows are told by id and text, since an id may be null or stand for several texts
    rows = judged(candidates(docs, id_col, text_col, digest=True, **cols))
    live = rows.select(F.col("doc_id").alias("_id"), F.col("digest").alias("_d"), F.filter("judged", lambda s: s["live"]).alias("_live")).where("size(_live) > 0")
    live = live.groupBy("_id", "_d").agg(F.first("_live").alias("_live"))
    text = F.col(text_col)

    def clean(piece, i):
        """A piece without the spans that reach into it; the mark stands where a span begins."""
        low = i * PIECE
        mine = F.filter("_live", lambda s: (s["start"] < low + PIECE) & (s["end"] > low))
        rest = lambda at, end: F.substring(piece, at - low + 1, end - at)
        step = lambda acc, s: F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(s["start"] >= acc["at"], F.concat(acc["out"], rest(acc["at"], s["start"]), F.lit(mark))).otherwise(acc["out"]).alias("out"))
        return F.aggregate(mine, F.struct(low.alias("at"), F.lit("").alias("out")), step, lambda acc: F.when(acc["at"] < low + PIECE, F.concat(acc["out"], rest(acc["at"], low + PIECE))).otherwise(acc["out"]))

    cleaned = F.array_join(F.transform(F.regexp_extract_all(text, F.lit(f"(?s).{{1,{PIECE}}}"), F.lit(0)), clean), "")
    out = docs.join(live.hint("shuffle_hash"), matched([F.col(id_col), text_digest(text)], [F.col("_id"), F.col("_d")]), "left").withColumn(text_col, F.when(F.col("_live").isNull(), text).otherwise(cleaned))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_live").isNull(), F.col("n_chars")).otherwise(F.char_length(text_col)).cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)
