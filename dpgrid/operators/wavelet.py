"""Wavelet transforms of count matrices held as rows of cells.

Haar blocks are plain grouped sums. Other filters run one axis at a time: each cell sends its value, times a tap, to
the outputs that the tap feeds, with circular indices. Only non-zero cells send anything, so sparse matrices stay sparse.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, replace
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.operators.grid import GridSpec, block_of, coordinates, linear

_R2, _R3 = math.sqrt(2), math.sqrt(3)


@dataclass(frozen=True)
class Wavelet:
    """Low- and high-pass taps; output ``q`` reads inputs from ``2 q + offset`` on."""

    name: str
    low: tuple[float, ...]
    high: tuple[float, ...]
    offset: int = 0
    high_offset: int = 0

    @property
    def haar(self) -> bool:
        return len(self.low) == 2 and self.low[0] == self.low[1]


def _mirror(low: tuple[float, ...]) -> tuple[float, ...]:
    """High-pass of an orthogonal filter: reversed, with alternating signs."""
    return tuple((-1) ** i * t for i, t in enumerate(reversed(low)))


_D4 = tuple(t / (4 * _R2) for t in (1 + _R3, 3 + _R3, 3 - _R3, 1 - _R3))
_D6 = tuple(
    t * _R2 / 32
    for t in (
        1 + math.sqrt(10) + math.sqrt(5 + 2 * math.sqrt(10)),
        5 + math.sqrt(10) + 3 * math.sqrt(5 + 2 * math.sqrt(10)),
        10 - 2 * math.sqrt(10) + 2 * math.sqrt(5 + 2 * math.sqrt(10)),
        10 - 2 * math.sqrt(10) - 2 * math.sqrt(5 + 2 * math.sqrt(10)),
        5 + math.sqrt(10) - 3 * math.sqrt(5 + 2 * math.sqrt(10)),
        1 + math.sqrt(10) - math.sqrt(5 + 2 * math.sqrt(10)),
    )
)
#: Published filter taps, low-pass normalised to a sum of the square root of two.
REGISTRY: dict[str, Wavelet] = {
    "haar": Wavelet("haar", (1 / _R2, 1 / _R2), (1 / _R2, -1 / _R2)),
    "db2": Wavelet("db2", _D4, _mirror(_D4)),
    "db3": Wavelet("db3", _D6, _mirror(_D6)),
    "bior2.2": Wavelet("bior2.2", tuple(_R2 * t for t in (-1 / 8, 1 / 4, 3 / 4, 1 / 4, -1 / 8)), tuple(_R2 * t for t in (-1 / 4, 1 / 2, -1 / 4)), -2, 0),
}


def register_wavelet(w: Wavelet) -> None:
    REGISTRY[w.name] = w


def get_wavelet(w: str | Wavelet) -> Wavelet:
    return REGISTRY[w] if isinstance(w, str) else w


def haar_scale(spec: GridSpec, level: int, scale: str) -> float:
    """Divisor of a block's sum."""
    return 2.0 ** (spec.n * level / 2) if scale == "orthonormal" else 2.0 ** (spec.n * level)


def wavelet_transform(
    counts: DataFrame, spec: GridSpec, wavelet: str | Wavelet = "haar", level: int = 1, value: str = "cnt", by: Sequence[str] = (), scale: str = "orthonormal", bands: str = "average"
) -> DataFrame:
    """``by..., wcell, w`` of the average band, or with ``bands="all"`` also the detail bands in column ``band``.

    Absent cells are zeros on both sides. Haar pads an odd edge with zeros; other filters wrap around. ``level`` repeats the step on
    the average band, which for Haar is one grouped sum. A band is named by a letter per axis: L low-pass, H high-pass.
    """
    w = get_wavelet(wavelet)
    if level < 1 or scale not in ("orthonormal", "mean") or bands not in ("average", "all"):
        raise ValueError("unknown level, scale or bands")
    if w.haar and bands == "average":
        total = counts.groupBy(*by, block_of(F.col("cell"), spec, level).alias("wcell")).agg(F.sum(F.col(value).cast("double")).alias("w"))
        return total.withColumn("w", F.col("w") / haar_scale(spec, level, scale))
    down = 1.0 if scale == "orthonormal" else 2.0 ** (-spec.n / 2)
    at, own = counts.select(*by, "cell", F.col(value).cast("double").alias("w")), spec
    for step in range(level):
        last = step == level - 1
        if w.haar:
            own = replace(own, g=tuple(k + k % 2 for k in own.g))
            if own.g != spec.g and step == 0:
                at = at.withColumn("cell", linear(coordinates(F.col("cell"), spec.g), own.g))
        at = _step(at, own, w, by, "all" if last and bands == "all" else "average", down)
        own = replace(own, g=own.coarse(1))
        if not last:
            at = at.withColumnRenamed("wcell", "cell")
    return at


def _step(at: DataFrame, spec: GridSpec, w: Wavelet, by: Sequence[str], bands: str, down: float) -> DataFrame:
    """One level: every axis in turn, halving it."""
    names = [f"_i{a}" for a in range(spec.n)]
    rows = at.select(*by, F.lit("").alias("band"), *[c.alias(n) for c, n in zip(coordinates(F.col("cell"), spec.g), names, strict=True)], "w")
    for axis, (name, g) in enumerate(zip(names, spec.g, strict=True)):
        half = -(-g // 2)
        kinds = [("L", w.low, w.offset)] + ([("H", w.high, w.high_offset)] if bands == "all" else [])
        # Output q takes input (2q + t + offset) mod g with tap t: for each input and tap, all q of that residue.
        feeds = [F.struct(F.lit(k).alias("k"), F.lit(t + o).alias("s"), F.lit(float(c)).alias("c")) for k, taps, o in kinds for t, c in enumerate(taps)]
        sent = rows.select("*", F.explode(F.array(*feeds)).alias("f"))
        outs = F.filter(F.sequence(F.lit(0), F.lit(half - 1)), lambda q: F.pmod(q * 2 + F.col("f.s"), F.lit(g)) == F.col(name)) if g <= 8 or g % 2 else _even_outputs(F.col(name), F.col("f.s"), g)
        sent = sent.select(*by, F.concat("band", "f.k").alias("band"), *[n for n in names if n != name], F.explode(outs.cast("array<bigint>")).alias(name), (F.col("w") * F.col("f.c")).alias("w"))
        rows = sent.groupBy(*by, "band", *names).agg(F.sum("w").alias("w"))
    wcell = linear([F.col(n) for n in names], spec.coarse(1))
    made = rows.select(*by, "band", wcell.alias("wcell"), (F.col("w") * down).alias("w"))
    return made if bands == "all" else made.drop("band")


def _even_outputs(i, s, g: int):
    """The outputs of an even axis that read input ``i`` through shift ``s``: one or none."""
    q = F.floor(F.pmod(i - s, F.lit(g)) / 2).cast("int")
    return F.when(F.pmod(i - s, F.lit(2)) == 0, F.array(q)).otherwise(F.array().cast("array<int>"))


def influence(w: str | Wavelet, n: int) -> list[tuple[int, int]]:
    """Numbers of positive and negative coefficients that one count feeds, by the parity of its index per axis."""
    taps = get_wavelet(w)
    own = []
    for phase in (0, 1):
        mine = [c for t, c in enumerate(taps.low) if (t + taps.offset) % 2 == phase and abs(c) > 1e-15]
        own.append((sum(c > 0 for c in mine), sum(c < 0 for c in mine)))
    found = set()
    for phases in product((0, 1), repeat=n):
        pos, neg = 1, 0
        for ph in phases:
            a, b = own[ph]
            pos, neg = pos * a + neg * b, pos * b + neg * a
        found.add((pos, neg))
    return sorted(found, reverse=True)


def sensitivity_z(w: str | Wavelet, n: int = 2, neighbor: str = "add_remove") -> int:
    """Most that one record changes the number of non-positive coefficients."""
    most = max(max(p) for p in influence(w, n))
    return most if neighbor == "add_remove" or get_wavelet(w).haar else 2 * most


def sensitivity_rank(w: str | Wavelet, n: int = 2, neighbor: str = "add_remove") -> int:
    """Most that one record changes the distance between a value's rank and the cut's."""
    most = 1 if get_wavelet(w).haar else max(sum(p) for p in influence(w, n))
    return most if neighbor == "add_remove" else 2 * most


def sensitivity_count(neighbor: str = "add_remove") -> int:
    """Most that one record changes the counts, summed over cells."""
    if neighbor not in ("add_remove", "replace"):
        raise ValueError(f"neighbours {neighbor!r}")
    return 1 if neighbor == "add_remove" else 2
