"""What a sketch is: register count, hash, seed.  Tables of different specs can't be merged."""

from __future__ import annotations

from dataclasses import asdict, dataclass


@dataclass(frozen=True)
class SketchSpec:
    """p: 2**p registers.  hash: ``xx`` (64 bits, JVM code) or ``portable`` (60 bits of md5, same in any SQL engine).
    rank: ``lead`` (leading zeros) or ``trail`` (trailing zeros, same distribution).  bits: word size, for ablation.
    dense_at: share of registers from which a packed sketch is stored densely."""

    p: int = 12
    hash: str = "xx"
    seed: int = 0
    rank: str = "lead"
    bits: int | None = None
    dense_at: float = 0.25

    def __post_init__(self):
        if not 4 <= self.p <= 18:
            raise ValueError(f"p is {self.p}; 4 to 18 are supported")
        if self.hash not in ("xx", "portable") or self.rank not in ("lead", "trail"):
            raise ValueError(f"unknown hash or rank form: {self.hash}, {self.rank}")
        if self.bits is not None and not self.p + 4 <= self.bits <= self.full_bits:
            raise ValueError(f"a word of {self.bits} bits does not fit")

    @property
    def full_bits(self) -> int:
        return 64 if self.hash == "xx" else 60

    @property
    def width(self) -> int:
        return self.bits or self.full_bits

    @property
    def q(self) -> int:
        return self.width - self.p

    @property
    def r(self) -> int:
        return 1 << self.p

    def as_dict(self) -> dict:
        return asdict(self)


PORTABLE8 = SketchSpec(p=8, hash="portable")


def assert_compatible(a: SketchSpec, b: SketchSpec) -> None:
    """Sketches merge or intersect only if made alike (storage form aside)."""
    differ = [k for k, v in a.as_dict().items() if k != "dense_at" and b.as_dict()[k] != v]
    if differ:
        raise ValueError(f"sketch tables differ in {', '.join(differ)}")
