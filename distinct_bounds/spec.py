"""What a sketch looks like: lanes, rows, refinement bits and the layout of a hash word."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass


@dataclass(frozen=True)
class SketchSpec:
    """c0 lanes of 2**r0 rows; z0 refinement bits.

    layout "hexslice" takes the row from the first hex digits of a word, the refinement from
    its last ones and the first-one field from those between (r0 and z0 must be multiples
    of 4); "prefix" takes row, refinement and first-one bits one after the other. family is
    the hash: "sha2" splits one SHA-256 (SHA-512 for more than 4 lanes), "md5" and "xxhash64"
    are seeded once a lane. Rows of a "prefix" word are read from the most significant bit,
    or from the least with row_bits="lsb". word_r0 and word_z0 say how many row and refinement
    bits a word is cut into, where that is more than the slots keep (a folded sketch): of
    either the highest are used, and the first-one field is what the cut leaves.
    """

    c0: int = 4
    r0: int = 4
    z0: int = 8
    family: str = "sha2"
    layout: str = "hexslice"
    row_bits: str = "msb"
    word_r0: int | None = None
    word_z0: int | None = None

    def __post_init__(self):
        for name, least in (("word_r0", self.r0), ("word_z0", self.z0)):
            if getattr(self, name) is None:
                object.__setattr__(self, name, least)
            if not least <= getattr(self, name) <= 16:
                raise ValueError(f"{name} is at least what the slots keep and at most 16")
        if self.c0 < 1 or not 0 <= self.r0 <= 16 or not 0 <= self.z0 <= 16:
            raise ValueError("c0 >= 1 and 0 <= r0, z0 <= 16 are asked for")
        if self.family not in ("sha2", "md5", "xxhash64") or self.layout not in ("hexslice", "prefix") or self.row_bits not in ("msb", "lsb"):
            raise ValueError(f"unknown choice in {self}")
        if self.layout == "hexslice" and (self.word_r0 % 4 or self.word_z0 % 4):
            raise ValueError("hexslice cuts words at hex digits: their row and refinement bits must be multiples of 4")
        if self.family == "sha2" and self.c0 > 8:
            raise ValueError("a split digest has at most 8 lanes of 64 bits")

    @property
    def rows(self) -> int:
        return 1 << self.r0

    @property
    def slots(self) -> int:
        return self.c0 << self.r0

    @property
    def p(self) -> float:
        return 2.0**-self.r0

    @property
    def first_one_bits(self) -> int:
        return 64 - self.word_r0 - self.word_z0

    @property
    def saturated(self) -> int:
        """The first-one position that stands for a field without a one."""
        return self.first_one_bits + 1

    @property
    def steps(self) -> int:
        return 1 << self.z0

    def fingerprint(self) -> str:
        """Names the slots that may be merged: sketches of different fingerprints must not be."""
        return hashlib.sha256(repr(self).encode()).hexdigest()[:12]

    @classmethod
    def hll_shape(cls, r0: int = 4, **more) -> SketchSpec:
        """One lane without refinement: the registers of the usual loglog family."""
        return cls(c0=1, r0=r0, z0=0, **more)

    @classmethod
    def single_slot(cls, c0: int = 1, **more) -> SketchSpec:
        """One row a lane, without refinement."""
        return cls(c0=c0, r0=0, z0=0, **more)
