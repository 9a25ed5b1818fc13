"""Hash words, register index and rank as JVM expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .spec import SketchSpec


def hash_word(element: Column, spec: SketchSpec, seed: int | Column | None = None) -> Column:
    """A word of spec.width bits for each element; equal in all tables of a spec.  seed: instead of the spec's, a
    number or an int column."""
    seed = spec.seed if seed is None else seed
    seed = seed if isinstance(seed, Column) else F.lit(seed)
    if spec.hash == "portable":
        word = F.conv(F.substring(F.md5(F.concat(F.lit("s"), seed.cast("string"), F.lit(":"), element.cast("string"))), 1, 15), 16, 10).cast("long")
    else:
        word = F.xxhash64(seed, element)
    cut = spec.full_bits - spec.width
    return F.shiftrightunsigned(word, cut) if cut else word


def index_of(word: Column, spec: SketchSpec) -> Column:
    return F.shiftrightunsigned(word, spec.q).cast("int")


def rank_of(word: Column, spec: SketchSpec) -> Column:
    """1 plus the leading (or trailing) zeros of the low q bits; q + 1 where they are all zero."""
    low = word.bitwiseAND(F.lit((1 << spec.q) - 1))
    if spec.rank == "trail":
        zeros = F.bit_count(low.bitwiseAND(-low) - 1) + 1
        return F.when(low == 0, F.lit(spec.q + 1)).otherwise(zeros).cast("int")
    # a doubled word with its last bit set has one digit more than the word, and one where the word is zero
    return (F.lit(spec.q + 2) - F.length(F.bin(F.shiftleft(low, 1).bitwiseOR(F.lit(1).cast("long"))))).cast("int")


def uniform(element: Column, seed: int) -> Column:
    """A number in [0, 1) from the portable hash: decisions of samplers, the same in any SQL engine."""
    word = F.conv(F.substring(F.md5(F.concat(F.lit(f"s{seed}:"), element.cast("string"))), 1, 13), 16, 10).cast("long")
    return word.cast("double") / F.lit(float(1 << 52))
