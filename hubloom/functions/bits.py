"""Hub sets as bits: column expressions over words of 63 hubs, and driver-side tags."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 63


def n_words(k: int) -> int:
    return max(1, -(-k // WORD))


def words_of(mask: int, n: int) -> list[int]:
    """A set of hubs as ``n`` words."""
    return [(mask >> (WORD * w)) & ((1 << WORD) - 1) for w in range(n)]


def mask_of(words: list[int]) -> int:
    return sum((w or 0) << (WORD * i) for i, w in enumerate(words))


def names(side: str, n: int) -> list[str]:
    return [f"{side}{w}" for w in range(n)]


def any_bit(side: str, n: int) -> Column:
    out = F.col(f"{side}0") != 0
    for w in range(1, n):
        out = out | (F.col(f"{side}{w}") != 0)
    return out


def count_bits(side: str, n: int) -> Column:
    out = F.bit_count(f"{side}0")
    for w in range(1, n):
        out = out + F.bit_count(f"{side}{w}")
    return out.cast("long")


def cardinality(n: int) -> Column:
    """Size of the product of a tag's two sets."""
    return count_bits("s", n) * count_bits("r", n)


def has_hub(side: str, hub: int) -> Column:
    return F.shiftright(F.col(f"{side}{hub // WORD}"), hub % WORD).bitwiseAND(F.lit(1)) == 1


def _members_of_word(side: str, w: int, n: int) -> Column:
    word = F.col(f"{side}{w}")
    numbers = F.array(*[F.lit(i) for i in range(n)]) if n > 0 else F.array().cast("array<int>")
    found = F.filter(numbers, lambda i: F.call_function("shiftright", word, i).bitwiseAND(F.lit(1).cast("long")) == 1)
    return F.transform(found, lambda i: i + WORD * w) if w else found


def members(side: str, k: int) -> Column:
    """The hub numbers of a set, ascending."""
    parts = [_members_of_word(side, w, min(WORD, k - WORD * w)) for w in range(n_words(k))]
    return parts[0] if len(parts) == 1 else F.concat(*parts)


@dataclass(frozen=True, order=True)
class Tag:
    """The hub pairs ``S x R`` an element belongs to."""

    s: int
    r: int

    @classmethod
    def of(cls, s: set[int] | list[int], r: set[int] | list[int]) -> Tag:
        return cls(sum(1 << i for i in set(s)), sum(1 << i for i in set(r)))

    def __len__(self) -> int:
        return self.s.bit_count() * self.r.bit_count()

    def __and__(self, other: Tag) -> Tag:
        return Tag(self.s & other.s, self.r & other.r)

    def minus(self, other: Tag) -> list[Tag]:
        """The pairs of this tag that are not in ``other``: at most two disjoint products."""
        both = self & other
        if not len(both):
            return [self] if len(self) else []
        parts = [Tag(self.s & ~both.s, self.r), Tag(both.s, self.r & ~both.r)]
        return [t for t in parts if len(t)]

    def pairs(self, diagonal: bool = False) -> set[tuple[int, int]]:
        xs = [i for i in range(self.s.bit_length()) if self.s >> i & 1]
        ys = [i for i in range(self.r.bit_length()) if self.r >> i & 1]
        return {(x, y) for x in xs for y in ys if diagonal or x != y}

    def size(self, diagonal: bool = False) -> int:
        """Number of pairs; without the diagonal, pairs of a hub with itself don't count."""
        return len(self) - (0 if diagonal else (self.s & self.r).bit_count())
