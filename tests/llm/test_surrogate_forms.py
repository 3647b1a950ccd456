"""Every form of one value gets one surrogate of its kind, and surrogates of unlike values are unlike."""

import re
from collections import defaultdict

import pytest

from docprofile.llm import pii


def replaced(spark, rows):
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    return {r.doc_id: r.text for r in pii.replace(df, b"k").collect()}


def mapping(rows, got):
    """(kind, canonical value) to its canonical surrogates, read off the texts by their unchanged rests."""
    seen = defaultdict(set)
    for i, t in rows:
        parts = [p for _, _, _, ps in pii.detections(t) for p in ps]
        pattern, last = "", 0
        for k, a, b, _ in parts:
            pattern += re.escape(t[last:a]) + (r"(.+?)" if k in ("given", "family", "email", "ipv6") else "(" + re.sub(r"\\?[0-9A-Z]", "[0-9A-Z]", re.escape(t[a:b])).replace("[0-9A-Z]" * 4 + r"\.", r"\d+\.") + "|[\\d.]+)")
            last = b
        m = re.fullmatch(pattern + re.escape(t[last:]), got[i], re.S)
        assert m, (t, got[i])
        for (k, a, b, _), new in zip(parts, m.groups(), strict=True):
            seen[k, pii.canonical(k, t[a:b])].add(pii.canonical(k, new))
    return seen


def one_to_one(seen):
    assert all(len(v) == 1 for v in seen.values()), {k: v for k, v in seen.items() if len(v) > 1}
    results = [(k, next(iter(v))) for (k, _), v in seen.items()]
    assert len(set(results)) == len(results) and not set(results) & set(seen)


def test_forms_share_a_surrogate(spark):
    rows = [
        (1, "Dr Anna Smith and Mrs Anna Smith; then Mrs Smith. Later Smith left, and Anna."), (2, "Mr Paul Smith met Miss Anna Lee-Young"), (3, "Herr Kim Day; Frau Kim Day"), (4, "call +1 (386) 555-3733 or 1-386-555-3733, tel 3865553733"),
        (5, "Herr José María Núñez kam. Núñez ging."), (6, "Prof Ελένη Παπά, Mr 王小明, Госпожа Иванова, Herr Ludwig van der Berg."), (7, "Mr JOHN SMITH, Mr John Smith"),
        (8, "at 2001:0db8:0000:0000:0000:ff00:0042:8329 or 2001:db8::ff00:42:8329, pay GB82 WEST 1234 5698 7654 32 or GB82WEST12345698765432"),
    ]
    rows += [(10 + i, f"{'Dr' if i % 2 else 'Mr'} Jo Ab{chr(97 + i % 26)}{chr(97 + i // 26)} again {'Mr' if i % 2 else 'Frau'} Jo Ab{chr(97 + i % 26)}{chr(97 + i // 26)}") for i in range(200)]
    got = replaced(spark, rows)
    seen = mapping(rows, got)
    one_to_one(seen)
    assert not any(re.search(r"Smith|Núñez|José|María|Anna\b|Παπά|王|Иванова|Berg|SMITH", t) for t in got.values() if "Anna" not in t) and "van der" in got[6]
    new = lambda k, v: next(iter(seen[k, v]))
    assert new("given", "paul").capitalize() in pii.NAMES["m"]["latin"] and pii.script(new("given", "ελένη")) == "greek" and pii.script(new("family", "王小明")) == "cjk" and pii.script(new("family", "иванова")) == "cyrillic"
    gender = lambda name: {g for g in "fmn" if name.capitalize() in pii.NAMES[g]["latin"] or name.endswith(pii.ENDINGS["latin"][g])}
    assert "f" in gender(new("given", "anna")) and "n" in gender(new("given", "kim")) and "n" in gender(new("given", "jo"))
    assert re.fullmatch(r"call \+1 \(\d{3}\) \d{3}-\d{4} or 1-\d{3}-\d{3}-\d{4}, tel \d{10}", got[4])
    a, b = re.fullmatch(r"at (\S+) or (\S+), pay (?:GB\d\d [A-Z]{4}( \d{4}){3} \d\d) or GB\d\d\w{18}", got[8]).groups()[:2]
    assert len(a) == 39 and pii.remainder(re.search(r"or (GB\w+)$", got[8])[1]) == 1
    assert got[7].split()[1].isupper() and got[7].split()[1].lower() == got[7].split()[4].lower()


def test_all_values_of_a_table(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    extra = [(10**6 + i, f"Mr Al{chr(97 + i % 26)} Fam{chr(97 + i // 26 % 26)} at {i % 7}.{i % 11}.{i % 13}.{i % 5} or u{i}@a.org") for i in range(600)]
    rows = [(i, t) for i, t in rows + extra if t]
    got = replaced(spark, rows)
    seen = mapping(rows, got)
    one_to_one(seen)
    assert len(seen) > 1000 and {k for k, _ in seen} >= {"given", "family", "ip", "email"}
    assert all(got[i] == t for i, t in rows if not pii.detections(t))


def test_tries_settle_collisions(spark, monkeypatch):
    rows = [(i, f"u{i}@real.org a1@x.example") for i in range(20)]
    small = lambda key, kind, value, trait=0, tries=0: f"a{(sum(map(ord, value)) + tries) % 40}@x.example"
    monkeypatch.setattr(pii, "surrogate", small)
    ruled = pii.resolve(spark.createDataFrame(rows, "doc_id long, text string").coalesce(1), b"k").collect()
    results = [small(b"k", r.kind, r.value, r.trait, r.tries) for r in ruled]
    assert len(set(results)) == len(ruled) == 21 and "a1@x.example" not in results and any(r.tries for r in ruled)


@pytest.mark.parametrize("text", ["12:30:45 and 1:2", "a::b c", "Mr. and Mrs", "Dr who", "tel 12", "1 234", "GB82 WEST 1234 5698 7654 33"])
def test_what_is_none(text):
    assert pii.find(text) == []
