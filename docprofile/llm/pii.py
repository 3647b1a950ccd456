"""Surrogates for personal data: keyed, of the same type and format, distinct for distinct values, the same everywhere.

Detected kinds: e-mail addresses, IPv4 and IPv6 addresses, payment card numbers (Luhn-valid, 13 to 19 digits), account
numbers (IBAN, check digits valid), telephone numbers (with marks between groups, or ten plain digits after a word for
telephone), social security numbers, and names: one or more capitalised words (or words of a script without capitals)
after a title, which tells a gender. Words of a name that a text gives after a title are also found without one in the
same text. Each word of a name is an entity of its own, the last one a family name, the others given names; so a full
name, a title with the family name and a bare family name agree wherever they stand.

A surrogate depends on the key, the kind, the canonical value and what is settled for that value over the corpus: a given
name's gender (of neither, where titles of both occur) and how many leading digits of a telephone number are a country's.
Addresses keep their shape, digits their places, cards and accounts stay valid, names keep gender, script and case. A
first pass gathers the distinct values; where two share a surrogate, or one is itself a value of the corpus, all but the
first try again with the next number of tries until none is left. What took more than one try, or isn't told by each
mention itself, goes to a table of hashed names in the shared folder that workers map and search, however long it is; the
second pass replaces texts where they are read, so no text is shuffled and nothing is collected.

Defined cases: null text stays null; empty texts stay; repeated rows each get a row; other columns are ignored; a null id
stays null; with overlapping detections the one that starts first, then the longer one, counts. Names without a title in
their text aren't found.
"""

from __future__ import annotations

import functools
import hashlib
import hmac
import ipaddress
import re
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import file_system, materialise, scratch, slices
from .hash_tables import Files, found, numbers, part_of, save, table

# Titles by gender, particles inside names, and given names by gender and script.
TITLES = {
    "f": ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Mlle", "Señora", "Sra", "Signora", "Госпожа", "Κυρία"),
    "m": ("Mr", "Herr", "Monsieur", "Señor", "Sr", "Signor", "Господин", "Κύριος"),
    "n": ("Dr", "Prof"),
}
PARTICLES = ("van", "von", "de", "der", "den", "del", "della", "di", "da", "dos", "la", "le", "bin", "al", "ten", "zu")
NAMES = {
    "f": {"latin": ("Anna", "Clara", "Diana", "Elena", "Greta", "Irene", "Julia", "Laura", "Maria", "Nora", "Paula", "Rosa", "Sara", "Vera"), "cyrillic": ("Анна", "Вера", "Елена", "Ирина", "Мария", "Ольга")},
    "m": {"latin": ("Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Hugo", "Jonas", "Leo", "Martin", "Oscar", "Paul", "Simon", "Victor"), "cyrillic": ("Антон", "Борис", "Иван", "Михаил", "Павел", "Сергей")},
    "n": {"latin": ("Alex", "Andrea", "Chris", "Dana", "Kim", "Robin", "Sasha", "Toni"), "cyrillic": ("Саша", "Женя", "Валя")},
}
SYLLABLES = {"latin": ("ba", "den", "fel", "gar", "hol", "kin", "lan", "mer", "nor", "ros", "sten", "ter", "vik", "wald"), "cyrillic": ("ба", "вол", "гор", "дан", "зим", "кол", "лев", "мор", "нов", "пет", "сок")}
#: Endings of made-up given names, by gender.
ENDINGS = {"latin": {"f": ("ia", "ina", "ela"), "m": ("us", "ert", "old"), "n": ("is", "ey", "in")}, "cyrillic": {"f": ("ина", "ия"), "m": ("ан", "ор"), "n": ("ли", "ше")}}

WORD = r"[^\W\d_]+(?:[-'’][^\W\d_]+)*"
#: Left of an @, and right of it.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}")
#: A run in which numbers may lie, and the kinds of numbers.
RUN = re.compile(r"\d[\d.() +-]*")
NUMBER = re.compile("|".join((
    r"(?P<ip>(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d))",
    r"(?P<ssn>(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-]))",
    r"(?P<card>(?<![\d.-])\d(?:[ -]?\d){12,18}(?![\d-]))",
    r"(?P<phone>(?<![\w.])(?:\+\d{1,3}[ .-]?)?(?:\(\d{1,4}\)[ .-]?|\d{1,4}[ .-])(?:\d{2,4}[ .-])*\d{3,4}(?![\w]))",
)))
CALL = re.compile(r"(?i)\b(?:tel|phone|call|mobile|cell|fax)[.:]?\x20{0,2}(?P<phone>[2-9]\d{2}[2-9]\d{6})(?!\w)")
IPV6 = re.compile(r"(?<![\w:.])[0-9A-Fa-f]{0,4}(?::[0-9A-Fa-f]{0,4}){2,7}(?![\w:])")
IBAN = re.compile(r"(?<!\w)[A-Z]{2}\d{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?!\w)")
ALL_TITLES = tuple(t for g in TITLES.values() for t in g)
TITLE = re.compile(rf"\b(?:{'|'.join(ALL_TITLES)})\.?(?=\x20)")
NEXT_WORD = re.compile(rf"\x20({WORD})")
GENDERS = ("n", "m", "f")
KINDS = ("email", "ip", "ipv6", "ssn", "card", "iban", "phone", "name")
#: Kinds of the words of a name.
GIVEN, FAMILY = "given", "family"


def luhn(digits: str) -> bool:
    d = [int(c) for c in reversed(digits)]
    return (sum(d[::2]) + sum(sum(divmod(2 * x, 10)) for x in d[1::2])) % 10 == 0


def remainder(account: str) -> int:
    """Of an account number by 97, its first four characters moved to its end and letters as numbers; 1 if it is valid."""
    return int("".join(str(int(c, 36)) for c in account[4:] + account[:4])) % 97


def _is_ipv6(value: str) -> bool:
    try:
        return len(value) > 4 and ipaddress.ip_address(value).version == 6
    except ValueError:
        return False


def _titled(text: str) -> list[tuple[int, list[tuple[int, int]], int]]:
    """(gender's place, words, end) of the names after titles."""
    out = []
    for m in TITLE.finditer(text):
        words, at = [], m.end()
        while w := NEXT_WORD.match(text, at):
            name = w[1]
            if name[0].islower() and not (name in PARTICLES and words):
                break
            words.append((w.start(1), w.end(1)))
            at = w.end()
        while words and text[words[-1][0] : words[-1][1]] in PARTICLES:
            words.pop()
        if words:
            gender = next(k for k, g in enumerate(GENDERS) if m[0].rstrip(".") in TITLES[g])
            out.append((gender, words, words[-1][1]))
    return out


def _names(text: str) -> list[tuple[str, int, int, list]]:
    """Names after titles, and words of them that stand elsewhere in the text."""
    out, known = [], {}
    for gender, words, _ in _titled(text):
        parts = []
        for i, (a, b) in enumerate(words):
            word = text[a:b]
            if word in PARTICLES:
                continue
            kind = FAMILY if i == len(words) - 1 else GIVEN
            told = gender if kind == GIVEN else 0
            parts.append((kind, a, b, told))
            known.setdefault(word, (kind, told))
        out.append(("name", words[0][0], words[-1][1], parts))
    again = sorted((w for w in known if len(w) > 2 or not w.isascii()), key=len, reverse=True)
    if again:
        taken = {a for _, _, _, parts in out for _, a, _, _ in parts}
        for m in re.finditer(rf"(?<!\w)(?:{'|'.join(map(re.escape, again))})(?!\w)", text):
            if m.start() not in taken:
                kind, told = known[m[0]]
                out.append(("name", m.start(), m.end(), [(kind, m.start(), m.end(), told)]))
    return out


def detections(text: str) -> list[tuple[str, int, int, list[tuple[str, int, int, int]]]]:
    """(kind, start, end, parts) left to right, parts (kind, start, end, what the mention tells) being what is replaced;
    cheap tests first, since most texts hold none."""
    spans = []
    at = text.find("@")
    while at >= 0:
        start = at
        while start and text[start - 1] in LOCAL:
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            spans.append(("email", start, m.end()))
        at = text.find("@", at + 1)
    for run in RUN.finditer(text):
        if run.end() - run.start() >= 7:
            for m in NUMBER.finditer(text, max(0, run.start() - 2), min(len(text), run.end() + 2)):
                if m.lastgroup == "card" and not luhn(re.sub(r"\D", "", m.group())):
                    continue
                if m.lastgroup == "phone" and len(re.sub(r"\D", "", m.group())) < 7:
                    continue
                spans.append((m.lastgroup, m.start(), m.end()))
            if run.end() - run.start() >= 10:
                spans += [("phone", *m.span("phone")) for m in CALL.finditer(text, max(0, run.start() - 12), run.end() + 1)]
                spans += [("iban", *m.span()) for m in IBAN.finditer(text, max(0, run.start() - 2), min(len(text), run.end() + 40)) if remainder(m[0].replace(" ", "")) == 1]
    if text.count(":") > 1:
        spans += [("ipv6", *m.span()) for m in IPV6.finditer(text) if _is_ipv6(m[0])]
    out = [(k, a, b, [(k, a, b, told(k, text[a:b]))]) for k, a, b in spans]
    if any(t in text for t in ALL_TITLES):
        out += _names(text)
    kept, last = [], 0
    for d in sorted(out, key=lambda d: (d[1], -d[2])):
        if d[1] >= last:
            kept.append(d)
            last = d[2]
    return kept


def find(text: str) -> list[tuple[str, int, int, str]]:
    """(kind, start, end, value) of each detection."""
    return [(k, a, b, text[a:b]) for k, a, b, _ in detections(text)]


def told(kind: str, form: str) -> int:
    """Digits of a telephone number after + that stay."""
    m = re.match(r"\+(\d{1,3})[ .(-]", form) if kind == "phone" else None
    return len(m[1]) if m else 0


def canonical(kind: str, form: str) -> str:
    """What all mentions of one entity share: letters without case, digits without their marks."""
    if kind in ("ssn", "card", "phone"):
        return re.sub(r"\D", "", form)
    if kind == "iban":
        return form.replace(" ", "")
    if kind == "ipv6":
        return ipaddress.ip_address(form).exploded
    return form.lower() if kind in ("email", GIVEN, FAMILY) else form


class Stream:
    """Numbers from a keyed hash."""

    def __init__(self, key: bytes, *what: str):
        self.key, self.what, self.n, self.left = key, "\x00".join(what).encode(), 0, b""

    def below(self, top: int) -> int:
        if len(self.left) < 4:
            self.left += hmac.new(self.key, self.what + self.n.to_bytes(4, "big"), hashlib.sha256).digest()
            self.n += 1
        out, self.left = int.from_bytes(self.left[:4], "big") % top, self.left[4:]
        return out

    def one(self, of):
        return of[self.below(len(of))]

    def digits(self, n: int) -> str:
        return "".join(str(self.below(10)) for _ in range(n))


def _spread(form: str, chars: str, replaced=str.isdigit) -> str:
    """chars at the places of form's characters that are replaced."""
    it = iter(chars)
    return "".join(next(it) if replaced(c) else c for c in form)


@functools.cache
def alphabet(block: int, category: str) -> str:
    """Letters of one category in a block of code points; of ideographs those that are in wide use begin the block."""
    low, high = (0x4E00, 0x6000) if 0x4E00 <= block << 8 < 0xA000 else (0xAC00, 0xD7A4) if 0xAC00 <= block << 8 < 0xD7A4 else (block << 8, (block + 1) << 8)
    return "".join(c for c in map(chr, range(low, high)) if unicodedata.category(c) == category and len(c.lower()) == 1 and not unicodedata.normalize("NFKC", c) != c)


def script(word: str) -> str:
    names = {unicodedata.name(c, "").split(" ")[0] for c in word if c.isalpha()}
    return names.pop().lower() if len(names) == 1 else "mixed"


def _word(s: Stream, kind: str, value: str, gender: str, tries: int) -> str:
    """A name of the value's script: from lists, made of syllables, or of other letters of the same alphabet."""
    kept = script(value)
    if kept in SYLLABLES:
        if kind == GIVEN and tries == 0:
            return s.one(NAMES[gender][kept]).lower()
        made = "".join(s.one(SYLLABLES[kept]) for _ in range((2 if kind == GIVEN else 3) + tries // 4))
        return made + (s.one(ENDINGS[kept][gender]) if kind == GIVEN else "")
    of = lambda c: alphabet(ord(c) >> 8, unicodedata.category(c)) or c
    made = "".join(s.one(of(c)) if c.isalpha() else c for c in value)
    return made + "".join(s.one(of(value[-1])) for _ in range(tries // 8))


def surrogate(key: bytes, kind: str, value: str, trait: int = 0, tries: int = 0) -> str:
    """Canonical surrogate of a canonical value. trait: a given name's gender's place, or the digits of a number that stay."""
    s = Stream(key, kind, value, str(tries))
    if kind == "email":
        local = "".join(chr(97 + s.below(26)) if c.isascii() and c.isalpha() else str(s.below(10)) if c.isdigit() else c for c in value.rpartition("@")[0])
        return f"{local}@{''.join(chr(97 + s.below(26)) for _ in range(8))}.example"
    if kind == "ip":
        return f"{1 + s.below(223)}.{s.below(256)}.{s.below(256)}.{s.below(256)}"
    if kind == "ipv6":
        return ipaddress.ip_address("2001:db8:" + ":".join(f"{s.below(65536):x}" for _ in range(6))).exploded
    if kind == "card":
        head = value[0] + s.digits(len(value) - 2)
        return next(head + str(c) for c in range(10) if luhn(head + str(c)))
    if kind == "iban":
        body = "".join(str(s.below(10)) if c.isdigit() else chr(65 + s.below(26)) for c in value[4:])
        return f"{value[:2]}{98 - remainder(value[:2] + '00' + body):02d}{body}"
    if kind == "ssn":
        return "9" + s.digits(len(value) - 1)
    if kind == "phone":
        return value[:trait] + s.digits(len(value) - trait)
    return _word(s, kind, value, GENDERS[trait], tries)


def dressed(kind: str, form: str, out: str) -> str:
    """A canonical surrogate in the marks and case of a mention."""
    if kind in ("ssn", "card", "phone"):
        return _spread(form, out)
    if kind == "iban":
        return _spread(form, out, str.isalnum)
    if kind == "ipv6":
        out = out if len(form) == 39 else ipaddress.ip_address(out).compressed
        return out.upper() if form.isupper() else out
    if kind == "email":
        local = form.rpartition("@")[0]
        return "".join(c.upper() if i < len(local) and local[i].isupper() else c for i, c in enumerate(out))
    if kind in (GIVEN, FAMILY):
        return out.upper() if form.isupper() and len(form) > 1 else out.capitalize() if form[:1].isupper() else out
    return out


def _hashes(pairs: list[tuple[str, str]]) -> np.ndarray:
    from xxhash import xxh64_intdigest

    return np.array([xxh64_intdigest(f"{k}\x00{v}".encode()) for k, v in pairs], np.uint64)


def resolve(docs: DataFrame, key: bytes, text_col: str = "text", max_tries: int = 64) -> DataFrame:
    """kind, value (canonical), trait, tries, mixed: how each value of the corpus gets a surrogate of its own; mixed says
    that some mention alone doesn't tell the trait."""
    def values(batches):
        for b in slices(batches):
            seen = {(k, canonical(k, t[i:j]), what) for t in b.column(0).to_pylist() if t for _, _, _, parts in detections(t) for k, i, j, what in parts}
            if seen:
                kinds, texts, what = zip(*sorted(seen), strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(kinds, pa.string()), pa.array(texts, pa.string()), pa.array(what, pa.int32())], ["kind", "value", "told"])

    mentions = docs.select(F.col(text_col).alias("text")).mapInArrow(values, "kind string, value string, told int")
    each = mentions.groupBy("kind", "value").agg(F.max("told").alias("most"), F.min("told").alias("least"), (F.max(F.col("told") == 1) & F.max(F.col("told") == 2)).alias("both"))
    # the mention that tells most speaks for all, but titles of both genders speak for neither
    trait = F.when((F.col("kind") == GIVEN) & F.col("both"), 0).otherwise(F.col("most"))
    each = materialise(each.select("kind", "value", trait.alias("trait"), (F.col("most") != F.col("least")).alias("mixed")), "values")
    taken = each.select("kind", F.col("value").alias("result"), F.lit("").alias("value"), F.lit(-1).alias("rank"))

    def results(batches):
        for b in batches:
            rows = b.to_pylist()
            yield b.append_column("result", pa.array([surrogate(key, r["kind"], r["value"], r["trait"], r["tries"]) for r in rows], pa.string()))

    schema = "kind string, value string, trait int, mixed boolean, tries int, result string"
    open_, settled = each.withColumn("tries", F.lit(0)), None
    for _ in range(max_tries):
        tried = materialise(open_.mapInArrow(results, schema), "tries")
        # a result belongs to a value of the corpus first, then to who settled on it, then to the smallest value that tries it
        rivals = taken if settled is None else taken.unionByName(settled.select("kind", "result", "value", F.lit(0).alias("rank")))
        best = rivals.unionByName(tried.select("kind", "result", "value", F.lit(1).alias("rank"))).groupBy("kind", "result").agg(F.min(F.struct("rank", "value")).alias("b"))
        ruled = materialise(tried.join(best, ["kind", "result"]).withColumn("won", (F.col("b.rank") == 1) & (F.col("b.value") == F.col("value"))).drop("b"), "ruled")
        won = ruled.where("won").drop("won")
        settled = won if settled is None else settled.unionByName(won)
        open_ = ruled.where("not won").select("kind", "value", "trait", "mixed", (F.col("tries") + 1).alias("tries"))
        if open_.isEmpty():
            return settled.select("kind", "value", "trait", "tries", "mixed")
    raise ValueError(f"values without a surrogate of their own after {max_tries} tries")


def write_table(ruled: DataFrame, range_keys: int = 1_000_000) -> tuple[str, int]:
    """Folder and ranges of the table of values whose surrogates a mention alone doesn't tell."""
    rows = ruled.where("tries > 0 or mixed").select("kind", "value", "trait", "tries")
    spark = rows.sparkSession
    folder = scratch(spark, "surrogates")
    fs, at = file_system(folder)
    fs.create_dir(at, recursive=True)
    ranges = max(1, -(-rows.count() // range_keys))

    def named(batches):
        for b in batches:
            h = _hashes(list(zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)))
            yield pa.RecordBatch.from_arrays([pa.array(part_of(h, 64, ranges).astype(np.int32)), pa.array(h.view(np.int64)), b.column(2), b.column(3)], ["part", "name", "trait", "tries"])

    def keep(key, t):
        names = t.column("name").to_numpy().view(np.uint64)
        order = np.argsort(names)
        save(folder, f"{key[0].as_py()}", table(names[order], {c: t.column(c).to_numpy()[order] for c in ("trait", "tries")}, True))
        return pa.table({"n": pa.array([len(names)], pa.int64())})

    made = rows.mapInArrow(named, "part int, name long, trait int, tries int").groupBy("part").applyInArrow(keep, "n long")
    materialise(made, "table")
    return folder, ranges


def replace(docs: DataFrame, key: bytes, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text (with surrogates), n_found, n_<kind> of each kind: one row a row of docs."""
    folder, ranges = write_table(resolve(docs, key, text_col))
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        files = Files(folder)

        def settled(mentions):
            """Traits and tries by (kind, value): what the table says, else what the mention tells and no second try."""
            pairs = list(mentions)
            out = dict(mentions)
            if pairs:
                names = _hashes(pairs)
                order = np.argsort(names)
                names, part = names[order], part_of(names[order], 64, ranges)
                for i in np.unique(part).tolist():
                    t = files(str(i))
                    if t is not None:
                        here = np.flatnonzero(part == i)
                        at = found(t, names[here])
                        hit = at >= 0
                        for p, trait, tries in zip(order[here[hit]].tolist(), numbers(t, "trait", at[hit]), numbers(t, "tries", at[hit]), strict=True):
                            out[pairs[p]] = (int(trait), int(tries))
            return out

        for b in slices(batches):
            texts = b.column(1).to_pylist()
            spotted = [detections(t) if t else [] for t in texts]
            mentions = {(k, canonical(k, t[i:j])): (what, 0) for t, ds in zip(texts, spotted, strict=True) for _, _, _, parts in ds for k, i, j, what in parts}
            made = {(k, v): surrogate(key, k, v, *how) for (k, v), how in settled(mentions).items()}
            out, counts = [], []
            for t, ds in zip(texts, spotted, strict=True):
                pieces, last, n = [], 0, dict.fromkeys(KINDS, 0)
                for group, _, _, parts in ds:
                    n[group] += 1
                    for k, i, j, _ in parts:
                        pieces += [t[last:i], dressed(k, t[i:j], made[k, canonical(k, t[i:j])])]
                        last = j
                out.append("".join(pieces) + t[last:] if pieces else t)
                counts.append(n)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.string()), pa.array([sum(n.values()) for n in counts], pa.int64()), *[pa.array([n[k] for n in counts], pa.int64()) for k in KINDS]], ["doc_id", "text", "n_found", *[f"n_{k}" for k in KINDS]])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, text string, n_found long, " + ", ".join(f"n_{k} long" for k in KINDS))
