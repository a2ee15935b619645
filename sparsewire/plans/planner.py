"""Choice of codecs from sizes: rules that need no data, and a chooser by predicted bits and measured time."""

from __future__ import annotations

from dataclasses import dataclass

from ..operators import index_codecs as ix
from ..operators import value_codecs as vc
from ..operators.theory import bits_per_key, p0_crossover
from .pipeline import Codec


@dataclass(frozen=True)
class Plan:
    """Source to sink as a tuple of steps; rules give a shorter or cheaper plan of the same meaning."""

    steps: tuple[str, ...]

    def without_bypasses(self) -> Plan:
        return Plan(tuple(s for s in self.steps if s not in ("identity", "raw_index", "raw_value")))

    def without_map(self, explicit_keys: bool) -> Plan:
        return Plan(tuple(s for s in self.steps if not (explicit_keys and s in ("pack_map", "unpack_map"))))


def key_form(r: int, d: int) -> ix.IndexCodec:
    """A bitmap where it is smaller than 32-bit keys."""
    return ix.BitmapKeys() if r * 32 > d else ix.RawKeys()


def p0_allowed(fpr: float, r: int, d: int) -> bool:
    return fpr < p0_crossover(r, d)


def predicted_bits(index: str, value: str, r: int, d: int, fpr: float = 0.01) -> float:
    positives = r + fpr * (d - r)
    n = positives if index == "bloom_p0" else r
    keys = {"raw": 32 * r, "bitmap": d, "bloom_p0": bits_per_key(fpr) * r, "bloom_p2": bits_per_key(fpr) * r, "delta": r * (2 + 8 * (1 if d < 256 * r else 2))}[index]
    values = {"none": 32 * n, "qsgd": (7 + 32 / 512) * n, "fit_poly": 8 * 6 * 32, "fit_dexp": 128 + n, "half": 16 * n}[value]
    mapped = n * max(1, int(n).bit_length()) if value.startswith("fit") and index != "raw" else 0
    return keys + values + mapped


SPEED = {"raw": 0, "bitmap": 1, "delta": 2, "bloom_p0": 3, "bloom_p2": 9, "none": 0, "half": 1, "qsgd": 1, "fit_poly": 3, "fit_dexp": 9}


def choose_codec(r: int, d: int, fpr: float = 0.01, weight: float = 0.0, lossless: bool = False) -> tuple[str, str]:
    """The pair of least predicted bits plus weight times relative effort; none is best for every tensor."""
    pairs = [(i, v) for i in ("raw", "bitmap", "delta", "bloom_p0", "bloom_p2") for v in ("none", "half", "qsgd", "fit_poly", "fit_dexp")]
    if lossless:
        pairs = [(i, v) for i, v in pairs if v == "none" and i != "bloom_p2"]
    pairs = [p for p in pairs if p[0] != "bloom_p0" or p0_allowed(fpr, r, d) or r * 3 > d]
    return min(pairs, key=lambda p: (predicted_bits(*p, r, d, fpr) + weight * r * (SPEED[p[0]] + SPEED[p[1]]), p))


def build(pair: tuple[str, str], fpr: float = 0.01, seed: int = 0) -> Codec:
    index = {"raw": ix.RawKeys, "bitmap": ix.BitmapKeys, "delta": ix.DeltaKeys}.get(pair[0])
    value = {"none": vc.RawValues, "half": vc.HalfValues, "qsgd": vc.Qsgd, "fit_poly": vc.FitPoly, "fit_dexp": vc.FitDoubleExp}[pair[1]]
    return Codec(index() if index else ix.BloomKeys(fpr, pair[0].removeprefix("bloom_"), seed), value())
