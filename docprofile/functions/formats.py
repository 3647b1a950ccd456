"""String formats: one label a value, the first that matches in a fixed order."""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F

# Format names of JSON Schema in the order in which they are tried, most specific first.
FORMATS = {
    "date-time": r"^\d{4}-\d{2}-\d{2}[Tt ]\d{2}:\d{2}:\d{2}(\.\d+)?([Zz]|[+-]\d{2}:?\d{2})?$",
    "date": r"^\d{4}-(0[1-9]|1[0-2])-(0[1-9]|[12]\d|3[01])$",
    "time": r"^([01]\d|2[0-3]):[0-5]\d:[0-5]\d(\.\d+)?([Zz]|[+-]\d{2}:\d{2})?$",
    "uuid": r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    "ipv4": r"^((25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(25[0-5]|2[0-4]\d|1?\d?\d)$",
    "ipv6": r"^([0-9a-fA-F]{1,4}:){7}[0-9a-fA-F]{1,4}$",
    "email": r"^[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+$",
    "uri": r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^\s/?#]+[^\s]*$",
    "hostname": r"^([a-z0-9]([a-z0-9-]*[a-z0-9])?\.)+[a-z]{2,}$",
}


def label(value: Column) -> Column:
    """Format of a string by one test a format; null if none."""
    out = F.lit(None).cast("string")
    for name, pattern in reversed(FORMATS.items()):
        out = F.when(value.rlike(pattern), F.lit(name)).otherwise(out)
    return out


#: All formats as one alternation, each in a group that the others' groups don't shift.
COMBINED = "|".join(f"({re.sub(r'[(](?![?])', '(?:', p)})" for p in FORMATS.values())


def label_combined(value: Column) -> Column:
    """Same as `label`: a cheap guard (no format has under 5 characters or lacks all of the marks), one match, then its group."""
    guard = (F.char_length(value) >= 4) & value.rlike(r"[-:.@/]") & value.rlike(COMBINED)
    out = F.lit(None).cast("string")
    for i, name in reversed(list(enumerate(FORMATS, 1))):
        out = F.when(F.regexp_extract(value, COMBINED, i) != "", F.lit(name)).otherwise(out)
    return F.when(guard, out)


def labels_early_stop(paths: list, values: list) -> list:
    """Labels of one batch: a path whose values had two labels (or none) can't regain one, so its other values aren't tested."""
    tests = [(n, re.compile(p, re.A)) for n, p in FORMATS.items()]
    seen: dict = {}
    for p, v in zip(paths, values, strict=True):
        had = seen.get(p, "")
        if v is None or had is None:
            continue
        got = next((n for n, t in tests if t.match(v)), None)
        seen[p] = got if had in ("", got) else None
    return list(seen.items())
