"""Codecs for whole tensors: an index codec and a value codec, chosen freely, packed block by block into containers.

A block of one tensor is one Arrow group, so memory follows the block size, not the tensor. Containers carry their
payload sizes in bits by part; the receiver uses a container and the codec's name alone.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import index_codecs as ix
from ..operators import value_codecs as vc
from ..operators.baselines import three_lc_decode_cells, three_lc_encode_cells
from ..operators.sparsify import BLOCK

SCHEMA = (
    "tensor_id bigint, block int, step int, worker int, d bigint, r bigint, n_values bigint, idx_codec string, val_codec string, policy string, seed bigint, "
    "idx_payload binary, val_payload binary, map_payload binary, meta map<string,string>, bits_idx bigint, bits_val bigint, bits_map bigint, bits_meta bigint"
)
ARROW = {
    "tensor_id": pa.int64(), "block": pa.int32(), "step": pa.int32(), "worker": pa.int32(), "d": pa.int64(), "r": pa.int64(), "n_values": pa.int64(), "idx_codec": pa.string(), "val_codec": pa.string(), "policy": pa.string(), "seed": pa.int64(),
    "idx_payload": pa.binary(), "val_payload": pa.binary(), "map_payload": pa.binary(), "meta": pa.map_(pa.string(), pa.string()), "bits_idx": pa.int64(), "bits_val": pa.int64(), "bits_map": pa.int64(), "bits_meta": pa.int64(),
}


BITS_OF = ("bits_idx", "bits_val", "bits_map")


#: Columns of a container that a receiver reads, and those of them that are bytes.
HELD = ["tensor_id", "block", "d", "r", "n_values", "idx_payload", "val_payload", "map_payload", "bits_idx", "bits_val", "bits_map", "bits_meta"]
PAYLOADS = ("idx_payload", "val_payload", "map_payload")
#: Most blocks, and about the most keys, that are encoded together.
BLOCKS, CELLS = 512, 1 << 19


def squeezed(data: bytes) -> bytes:
    return len(data).to_bytes(8, "little") + pa.compress(data, "zstd", asbytes=True)


class Squeezed(dict):
    """A held container, whose payloads are expanded when they are read."""

    def __getitem__(self, name: str) -> object:
        x = super().__getitem__(name)
        return pa.decompress(x[8:], int.from_bytes(x[:8], "little"), "zstd", asbytes=True) if name in PAYLOADS else x


def alike(b: pa.RecordBatch) -> Iterator[list[int]]:
    """Rows of a batch that have equal block, d and r, at most BLOCKS and about CELLS keys of them at a time."""
    block, d, r = (b.column(c).to_numpy() for c in ("block", "d", "r"))
    order = np.lexsort((r, d, block))
    cut = np.flatnonzero((np.diff(block[order]) != 0) | (np.diff(d[order]) != 0) | (np.diff(r[order]) != 0)) + 1
    for rows in np.split(order, cut):
        if len(rows):
            few = max(1, min(BLOCKS, CELLS // max(1, int(r[rows[0]]))))
            yield from (rows[a : a + few].tolist() for a in range(0, len(rows), few))


def blocks_of(coo: DataFrame, d: int, size: int = BLOCK) -> DataFrame:
    """(tensor_id, block, d, r, keys, values): a row for each block that has cells, d being the block's width and keys
    its own, in order. coo may have a column block of its own, by which it is dealt already."""
    cells = coo if "block" in coo.columns else coo.withColumn("block", F.expr(f"CAST(idx div {size} AS INT)"))
    cells = cells.select("tensor_id", "block", F.expr(f"CAST(idx - block * {size}L AS INT)").alias("idx"), F.col("value").cast("double").alias("value"))

    def run(t: pa.Table) -> pa.Table:
        idx, value = t.column("idx").to_numpy(), t.column("value").to_numpy()
        order = np.argsort(idx)
        idx, block = idx[order], t.column("block")[0].as_py()
        if (idx[1:] == idx[:-1]).any():
            raise ValueError("a tensor has two cells of one index")
        cols = (pa.array([t.column("tensor_id")[0].as_py()], pa.int64()), pa.array([block], pa.int32()), pa.array([min(size, d - block * size)], pa.int64()), pa.array([len(idx)], pa.int64()), pa.array([idx], pa.list_(pa.int32())), pa.array([value[order]], pa.list_(pa.float64())))
        return pa.Table.from_arrays(cols, names=["tensor_id", "block", "d", "r", "keys", "values"])

    return cells.groupBy("tensor_id", "block").applyInArrow(run, "tensor_id bigint, block int, d bigint, r bigint, keys array<int>, values array<double>")


class Codec:
    """Any index codec with any value codec. fill 'dense' fetches values at false positives from the original."""

    def __init__(self, index: ix.IndexCodec | None = None, value: vc.ValueCodec | None = None, reorder: str = "auto", block: int = BLOCK) -> None:
        self.index, self.value, self.reorder, self.block = index or ix.RawKeys(), value or vc.RawValues(), reorder, block
        self.name = f"{self.index.name}+{self.value.name}"

    def encode_block(self, keys: np.ndarray, values: np.ndarray, d: int, block: int = 0, dense: Callable[[np.ndarray], np.ndarray] | None = None) -> dict:
        """One container row (without identifiers) of sorted keys in [0, d)."""
        if not np.isfinite(values).all():
            raise ValueError("values must be finite")
        e = self.index.encode(keys, d, block)
        sent = dense(e.sent) if dense is not None and e.sent is not keys else self._sent(e, keys, values)
        return self._container(e, self.value.encode(sent), len(keys), len(sent), d, block)

    @staticmethod
    def _sent(e: ix.Encoded, keys: np.ndarray, values: np.ndarray) -> np.ndarray:
        """Values of the indices that are sent, 0 at those that are no keys."""
        if e.sent is keys:
            return values
        if len(e.sent) > 16 * len(keys) and (e.sent[1:] > e.sent[:-1]).all():
            at = np.minimum(np.searchsorted(e.sent, keys), len(e.sent) - 1)
            hit, sent = e.sent[at] == keys, np.zeros(len(e.sent))
            sent[at[hit]] = values[hit]
            return sent
        at = np.minimum(np.searchsorted(keys, e.sent), max(len(keys) - 1, 0))
        return np.where(keys[at] == e.sent, values[at], 0.0)

    def _container(self, e: ix.Encoded, p: vc.Packed, r: int, n_values: int, d: int, block: int) -> dict:
        payload, mapped, bits_map = e.payload, b"", 0
        if p.order is not None:
            if self.index.explicit and self.reorder == "auto":
                payload = self.index.encode(e.sent[p.order], d, block).payload
            else:
                mapped, bits_map = vc.pack_map(p.order)
        return {
            "d": d, "r": r, "n_values": n_values, "idx_codec": self.index.name, "val_codec": self.value.name, "policy": getattr(self.index, "policy", None), "seed": getattr(self.index, "seed", 0),
            "idx_payload": payload, "val_payload": p.payload, "map_payload": mapped, "meta": [("block_size", str(self.block))], "bits_idx": e.bits, "bits_val": p.bits, "bits_map": bits_map, "bits_meta": e.meta_bits,
        }

    def decode_block(self, c: dict, block: int = 0) -> tuple[np.ndarray, np.ndarray]:
        return self._cells(c, self.index.decode(c["idx_payload"], c["d"], c["r"], c["n_values"], block))

    def _cells(self, c: dict, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = c["n_values"]
        values = self.value.decode(c["val_payload"], n)
        if self.value.reorders and not (self.index.explicit and self.reorder == "auto"):
            values = values[vc.unpack_map(c["map_payload"], n)] if n else values
        return keys[: len(values)], values[: len(keys)]

    def encode_many(self, keys: Sequence[np.ndarray], values: Sequence[np.ndarray], d: int, block: int = 0) -> Iterator[dict]:
        """encode_block of blocks of one number and width that have equally many keys."""
        if not all(np.isfinite(v).all() for v in values):
            raise ValueError("values must be finite")
        if self._few and len(keys[0]):
            made = list(self.index.filters(keys, block))
            accepted = self.index.accepted_many([p for p, _ in made], d, len(keys[0]), block)
            for k, v, (payload, bits), a in zip(keys, values, made, accepted, strict=True):
                p = self.value.encode_few(a.rank(k), v, len(a))
                yield self._container(ix.Encoded(payload, bits, k, 256), p, len(k), len(a), d, block)
            return
        found = zip(keys, values, self.index.encode_many(keys, d, block), strict=True)
        for part in itertools.batched(found, self.value.together):
            sent = [self._sent(e, k, v) for k, v, e in part]
            for (k, _, e), v, p in zip(part, sent, self.value.encode_many(sent), strict=True):
                yield self._container(e, p, len(k), len(v), d, block)

    def decode_many(self, containers: Sequence[dict], block: int = 0) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """decode_block of containers of one block's number and width that have equally many keys, some zeros left out."""
        d, r = containers[0]["d"], containers[0]["r"]
        if self._few and r:
            for c, a in zip(containers, self.index.accepted_many([c["idx_payload"] for c in containers], d, r, block), strict=True):
                at, values = self.value.decode_few(c["val_payload"], c["n_values"])
                yield a.nth(at), values
            return
        found = self.index.decode_many([c["idx_payload"] for c in containers], d, r, [c["n_values"] for c in containers], block)
        yield from map(self._cells, containers, found)

    @property
    def _few(self) -> bool:
        """Whether nearly all values that are sent are 0, and neither they nor their indices need be listed."""
        return isinstance(self.index, ix.BloomKeys) and self.index.dense and isinstance(self.value, vc.Qsgd)

    def encode_held(self, held: DataFrame) -> DataFrame:
        """Containers of blocks_of, as wide ones are best held until they are decoded: what each says, squeezed."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for at in alike(b):
                    block, d = (b.column(c)[at[0]].as_py() for c in ("block", "d"))
                    keys, values = ([b.column(c)[i].values.to_numpy() for i in at] for c in ("keys", "values"))
                    tensors = [b.column("tensor_id")[i].as_py() for i in at]
                    done = self.encode_many([k.astype(np.int64) for k in keys], values, d, block)
                    for part in itertools.batched(zip(tensors, done, strict=True), 64):
                        rows = [c | {"tensor_id": t, "block": block} | {x: squeezed(c[x]) for x in PAYLOADS} for t, c in part]
                        yield pa.RecordBatch.from_arrays([pa.array([c[n] for c in rows], ARROW[n]) for n in HELD], names=HELD)

        return held.mapInArrow(run, ", ".join(f"{n} {'int' if n == 'block' else 'binary' if n in PAYLOADS else 'bigint'}" for n in HELD))

    def decode_held(self, containers: DataFrame) -> DataFrame:
        """(tensor_id, idx, value) of what encode_held gives, zeros left out."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for at in alike(b):
                    rows = [Squeezed(c) for c in b.take(pa.array(at)).to_pylist()]
                    out, total, block = [], 0, rows[0]["block"]
                    for c, (keys, values) in zip(rows, self.decode_many(rows, block), strict=True):
                        keep = np.flatnonzero(values)
                        out.append((np.full(len(keep), c["tensor_id"]), keys[keep] + block * self.block, values[keep]))
                        total += len(keep)
                        if total >= 1 << 17:
                            yield self._batch(out)
                            out, total = [], 0
                    if out:
                        yield self._batch(out)

        return containers.mapInArrow(run, "tensor_id bigint, idx bigint, value double")

    @staticmethod
    def _batch(cells: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        columns = (np.concatenate(x) for x in zip(*cells, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["tensor_id", "idx", "value"])

    def encode(self, coo: DataFrame, meta: DataFrame, dense: DataFrame | None = None, step: int = 0, worker: int = 0) -> DataFrame:
        """Containers of all tensors. dense: the original tensor, for values at false positives."""
        size, fetch = self.block, dense is not None
        cells = coo.select("tensor_id", "idx", F.col("value").cast("double").alias("value"), F.lit(True).alias("hit"))
        if dense is not None:
            cells = dense.select("tensor_id", "idx", F.col("value").cast("double").alias("value")).join(cells.select("tensor_id", "idx", "hit"), ["tensor_id", "idx"], "left").withColumn("hit", F.coalesce("hit", F.lit(False)))
        rows = cells.join(meta.select("tensor_id", "d"), "tensor_id").withColumn("block", F.expr(f"CAST(idx div {size} AS INT)"))

        def run(t: pa.Table) -> pa.Table:
            idx, val, hit = (t.column(c).to_numpy() for c in ("idx", "value", "hit"))
            order = np.argsort(idx, kind="stable")
            idx, val, hit = idx[order], val[order], hit[order]
            if len(idx) > 1 and (idx[1:] == idx[:-1]).any():
                raise ValueError("a tensor has two cells of one index")
            tensor, block, d = (t.column(c)[0].as_py() for c in ("tensor_id", "block", "d"))
            lo = block * size
            local = idx - lo

            def at(keys: np.ndarray) -> np.ndarray:
                p = np.minimum(np.searchsorted(local, keys), len(local) - 1)
                return np.where(local[p] == keys, val[p], 0.0)

            c = self.encode_block(local[hit], val[hit], min(size, d - lo), block, at if fetch else None)
            c |= {"tensor_id": tensor, "block": block, "step": step, "worker": worker}
            return pa.table({k: pa.array([c[k]], kind) for k, kind in ARROW.items()})

        return rows.groupBy("tensor_id", "block").applyInArrow(run, SCHEMA)

    def decode(self, containers: DataFrame) -> DataFrame:
        """(tensor_id, idx, value) of all containers, zeros left out."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for c in b.to_pylist():
                    keys, values = self.decode_block(c, c["block"])
                    keep = values != 0
                    idx = keys[keep] + c["block"] * self.block
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(idx), c["tensor_id"]), pa.int64()), pa.array(idx, pa.int64()), pa.array(values[keep], pa.float64())], names=["tensor_id", "idx", "value"])

        cols = ["tensor_id", "block", "d", "r", "n_values", "idx_payload", "val_payload", "map_payload"]
        return containers.select(*cols).mapInArrow(run, "tensor_id bigint, idx bigint, value double")


class ThreeLC(Codec):
    """A dense ternary code: no index part."""

    def __init__(self, multiplier: float = 1.0, block: int = BLOCK) -> None:
        super().__init__(block=block)
        self.multiplier, self.name = multiplier, "3lc"

    def encode_block(self, keys, values, d, block=0, dense=None):
        scale, data = three_lc_encode_cells(keys, values, d, self.multiplier)
        return {"d": d, "r": len(keys), "n_values": d, "idx_codec": "dense", "val_codec": "3lc", "policy": None, "seed": 0, "idx_payload": b"", "val_payload": np.float64(scale).tobytes() + data, "map_payload": b"", "meta": [], "bits_idx": 0, "bits_val": 8 * len(data) + 32, "bits_map": 0, "bits_meta": 64}

    def decode_block(self, c, block=0):
        return three_lc_decode_cells(float(np.frombuffer(c["val_payload"][:8])[0]), c["val_payload"][8:], c["d"])

    def encode_many(self, keys, values, d, block=0):
        return (self.encode_block(k, v, d, block) for k, v in zip(keys, values, strict=True))

    def decode_many(self, containers, block=0):
        return (self.decode_block(c, block) for c in containers)


_REGISTRY: dict[str, Callable[..., object]] = {}


def register(name: str) -> Callable:
    """Class decorator: makes a user's index or value codec known by name."""

    def add(cls: Callable) -> Callable:
        _REGISTRY[name] = cls
        return cls

    return add


def registered(name: str, **params: object) -> object:
    return _REGISTRY[name](**params)


for _cls in (ix.RawKeys, ix.BitmapKeys, ix.RunLength, ix.HuffmanKeys, ix.DeltaKeys, ix.DeltaHuffmanKeys):
    register(_cls.name)(_cls)
for _name, _value in (("bloom", ix.BloomKeys), ("none", vc.RawValues), ("half", vc.HalfValues), ("deflate", vc.Deflate), ("qsgd", vc.Qsgd), ("fit_poly", vc.FitPoly), ("fit_dexp", vc.FitDoubleExp), ("quantile", vc.QuantileBuckets)):
    register(_name)(_value)


def sketchml(buckets: int = 64) -> Codec:
    return Codec(ix.DeltaKeys(), vc.QuantileBuckets(buckets))


def skcompress(bits: int = 7, split_sign: bool = False) -> Codec:
    return Codec(ix.DeltaHuffmanKeys(), vc.QuantileBuckets(2**bits, huffman=True, split_sign=split_sign), reorder="none")


def catalogue(fpr: float = 0.001, seed: int = 0) -> dict[str, Codec]:
    """Every instantiation that experiments compare, by name."""
    bloom = lambda p: ix.BloomKeys(fpr, p, seed)
    out = {"topr": Codec(), "bitmap": Codec(ix.BitmapKeys()), "rle": Codec(ix.RunLength()), "huffman": Codec(ix.HuffmanKeys()), "delta": Codec(ix.DeltaKeys())}
    out |= {f"bloom_{p}": Codec(bloom(p)) for p in ("naive", "p0", "p1", "p2", "left", "middle", "right")}
    out |= {"deflate": Codec(None, vc.Deflate()), "qsgd": Codec(None, vc.Qsgd(seed=seed)), "half": Codec(None, vc.HalfValues()), "fit_poly": Codec(None, vc.FitPoly()), "fit_dexp": Codec(None, vc.FitDoubleExp())}
    out |= {f"bloom_{p}+fit_poly": Codec(bloom(p), vc.FitPoly()) for p in ("p0", "p1", "p2")}
    out |= {f"bloom_{p}+qsgd": Codec(bloom(p), vc.Qsgd(seed=seed)) for p in ("p0", "p1", "p2")}
    return out | {"3lc": ThreeLC(), "sketchml": sketchml(), "skcompress": skcompress()}
