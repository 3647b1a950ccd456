"""Column functions on texts: path steps, common prefixes, portable hashes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def key_step(key: Column) -> Column:
    """Step of an object key: plain names as they are, others JSON-quoted."""
    quoted = F.concat(F.lit('"'), F.replace(F.replace(key, F.lit("\\"), F.lit("\\\\")), F.lit('"'), F.lit('\\"')), F.lit('"'))
    return F.concat(F.lit("."), F.when(key.rlike("^[A-Za-z_][A-Za-z0-9_]*$"), key).otherwise(quoted))


def common_prefix(a: Column, b: Column) -> Column:
    """Longest common prefix, in code points."""
    n = F.least(F.char_length(a), F.char_length(b))
    same = F.aggregate(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), F.lit(0), lambda acc, i: F.when((acc == i - 1) & (i <= n) & (F.substring(a, i, F.lit(1)) == F.substring(b, i, F.lit(1))), i).otherwise(acc))
    return F.substring(a, F.lit(1), same)


def bucket(key: Column, seed: int, buckets: int = 100) -> Column:
    """Bucket of a key by md5, the same in any engine that has md5."""
    return F.conv(F.substring(F.md5(F.concat(key.cast("string"), F.lit(f":{seed}"))), 1, 8), 16, 10).cast("long") % buckets


def regex_escape(s: str) -> str:
    import re

    return re.sub(r"([\\.^$|?*+()\[\]{}/-])", r"\\\1", s)
