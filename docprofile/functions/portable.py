"""Sketches whose hashes any engine with md5 can repeat: a HyperLogLog and a Bloom filter in plain rows."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

P, REGISTERS = 10, 1 << 10
BITS, HASHES = 8192, 4


def hex_number(text: Column, start: int, digits: int) -> Column:
    """Number of some hexadecimal digits of md5(text)."""
    return F.conv(F.substring(F.md5(text), start, digits), 16, 10).cast("long")


def hll_registers(facts: DataFrame) -> DataFrame:
    """typed_path, register, rank: the register by eight digits of the hash, the rank by the leading zeros of eight others."""
    rest = hex_number(F.col("text"), 9, 8)
    rank = F.when(rest == 0, F.lit(33)).otherwise(F.lit(32) - F.floor(F.log2(rest.cast("double")))).cast("int")
    rows = facts.where("text is not null and kind in ('string', 'number')")
    return rows.groupBy("typed_path", (hex_number(F.col("text"), 1, 8) % REGISTERS).alias("register")).agg(F.max(rank).alias("rank"))


def hll_estimate(registers: DataFrame) -> DataFrame:
    """typed_path, estimate (rounded): harmonic mean of the registers, with the linear count for small numbers."""
    alpha = 0.7213 / (1 + 1.079 / REGISTERS)
    s = registers.groupBy("typed_path").agg(F.sum(F.pow(F.lit(2.0), -F.col("rank"))).alias("s"), F.count(F.lit(1)).alias("used"))
    zero = F.lit(REGISTERS) - F.col("used")
    raw = F.lit(alpha * REGISTERS * REGISTERS) / (F.col("s") + zero)
    small = REGISTERS * F.log(F.lit(float(REGISTERS)) / zero)
    return s.select("typed_path", F.round(F.when((raw <= 2.5 * REGISTERS) & (zero > 0), small).otherwise(raw)).cast("long").alias("estimate"))


def bloom_bits(facts: DataFrame) -> DataFrame:
    """typed_path, bit: the bits that are set."""
    rows = facts.where("text is not null and kind in ('string', 'number')")
    return rows.select("typed_path", F.explode(positions(F.col("text"))).alias("bit")).distinct()


def positions(text: Column) -> Column:
    a, b = hex_number(text, 1, 8), hex_number(text, 9, 8)
    return F.array(*[(a + b * i) % BITS for i in range(HASHES)])


def bloom_subset(bits: DataFrame) -> DataFrame:
    """child, parent: pairs of paths where the child's bits are among the parent's. Counts of shared bits by an equi-join on
    the bit: at most BITS rows a path, so this is bounded by the schema."""
    n = bits.groupBy("typed_path").agg(F.count(F.lit(1)).alias("n"))
    a, b = bits.select(F.col("typed_path").alias("child"), "bit"), bits.select(F.col("typed_path").alias("parent"), "bit")
    shared = a.join(b, "bit").where("child <> parent").groupBy("child", "parent").agg(F.count(F.lit(1)).alias("shared"))
    return shared.join(n.withColumnRenamed("typed_path", "child"), "child").where("shared = n").select("child", "parent")


def standard_error() -> float:
    return 1.04 / math.sqrt(REGISTERS)
