"""Injective vertex priorities as Column expressions.

A priority is a ``long`` that depends on (vertex id, seed, phase) alone, so a task that
runs again draws the same order. Each mode is a bijection with a cheap inverse: the
owner of a label is found without a join.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

LOW_HALF = 0xFFFFFFFF
ROUNDS = 4
#: Fixed values of the affine mode: a multiplier, its prime modulus.
MULTIPLIER = 48271
MODULUS = 2147483647


def _halves(x: Column) -> tuple[Column, Column]:
    return F.shiftrightunsigned(x, 32), x.bitwiseAND(F.lit(LOW_HALF))


def _mix(half: Column, seed: int, phase: int, step: int) -> Column:
    return F.xxhash64(half, F.lit(seed), F.lit(phase), F.lit(step)).bitwiseAND(F.lit(LOW_HALF))


def permute64(x: Column, seed: int = 0, phase: int = 0) -> Column:
    """Balanced Feistel network over the two halves of a long: one-to-one on all longs."""
    left, right = _halves(x.cast("long"))
    for step in range(ROUNDS):
        left, right = right, left.bitwiseXOR(_mix(right, seed, phase, step))
    return F.shiftleft(left, 32).bitwiseOR(right)


def unpermute64(y: Column, seed: int = 0, phase: int = 0) -> Column:
    """Inverse of :func:`permute64`."""
    left, right = _halves(y)
    for step in reversed(range(ROUNDS)):
        left, right = right.bitwiseXOR(_mix(left, seed, phase, step)), left
    return F.shiftleft(left, 32).bitwiseOR(right)


def affine(x: Column, seed: int = 0) -> Column:
    """One-to-one for ids in [0, MODULUS); plain arithmetic that any SQL engine repeats."""
    return (x * F.lit(MULTIPLIER) + F.lit(seed)) % F.lit(MODULUS)


def unaffine(y: Column, seed: int = 0) -> Column:
    back = pow(MULTIPLIER, -1, MODULUS)
    shifted = F.pmod(y - F.lit(seed % MODULUS), F.lit(MODULUS))
    return F.pmod(shifted.cast("decimal(12,0)") * F.lit(back).cast("decimal(12,0)"), F.lit(MODULUS).cast("decimal(12,0)")).cast("long")


@dataclass(frozen=True)
class Priority:
    """A mode of drawing the order: ``permute`` (default), ``affine`` or ``identity``.

    ``identity`` takes the ids themselves as the order (a given order: choose the ids).
    """

    mode: str = "permute"
    seed: int = 0

    def __post_init__(self):
        if self.mode not in ("permute", "affine", "identity"):
            raise ValueError(f"unknown priority mode {self.mode}")

    def of(self, x: Column, phase: int = 0) -> Column:
        if self.mode == "permute":
            return permute64(x, self.seed, phase)
        return affine(x, self.seed + phase) if self.mode == "affine" else x

    def owner(self, y: Column, phase: int = 0) -> Column:
        if self.mode == "permute":
            return unpermute64(y, self.seed, phase)
        return unaffine(y, self.seed + phase) if self.mode == "affine" else y
