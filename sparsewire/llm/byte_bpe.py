"""Byte-level BPE encoding and decoding with the tokenizers library over Arrow batches.

Bytes travel through the library as printable characters (``byte_characters``); decoding reverses that table and
joins the bytes of all ids before it reads UTF-8, so characters split over several ids come back whole.

The library splits, spells and merges, and tells which characters each id covers. A text is cut at every space that
has no white space beside it first: the split pattern always starts a new match there and never looks past it, so the
pieces encode separately to what the whole text gives. Pieces repeat a lot; each worker remembers the ids and offsets
of those it has met and gives the library only new ones, a batch at a time.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import any_names, bounded_batches, give_back, table

#: Pieces that a worker remembers before it starts anew; bounds its memory, changes no result.
REMEMBERED = 60_000
#: Longer pieces are encoded each time they occur.
LONGEST_REMEMBERED = 64
#: New pieces that the library splits by one call.
LEARNED_AT_ONCE = 8_000
CUT = re.compile(r"(?<=\S) (?=\S)")


def vocabulary_path(name: str = "byte_bpe_50k.tiktoken") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_characters() -> list[str]:
    """The printable character that stands for each byte: itself where printable, else the next free code from 256."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b if b in plain else next(spare)) for b in range(256)]


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}


def _merges(ranks: dict[bytes, int]) -> list[tuple[bytes, bytes]]:
    """The pair that made each token: the one left when all merges of lower rank are done."""
    out = []
    for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
        parts = [token[i : i + 1] for i in range(len(token))]
        while len(parts) > 2:
            best = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], 1 << 60))
            if ranks.get(parts[best] + parts[best + 1], 1 << 60) >= rank:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        if len(parts) == 2:
            out.append((parts[0], parts[1]))
    return out


class Remembered:
    """What has been met lately: entries not asked for while as many new ones as the limit came are forgotten."""

    def __init__(self, most: int = REMEMBERED) -> None:
        self.most, self.new, self.old = most, {}, {}

    def get(self, keys: list[str]) -> list[bytes | None]:
        got = list(map(self.new.get, keys))
        if self.old:
            new, old = self.new, self.old
            for i, x in enumerate(got):
                if x is None:
                    found = old.get(keys[i])
                    if found is not None:
                        new[keys[i]] = got[i] = found
        return got

    def put(self, pairs: Iterable[tuple[str, bytes]]) -> None:
        self.new.update(pairs)
        if len(self.new) > self.most:
            self.new, self.old = {}, self.new

    def clear(self) -> None:
        self.new, self.old = {}, {}


class Codec:
    """Encoder and decoder of one rank file."""

    def __init__(self, path: str, pattern: str) -> None:
        from tokenizers import Regex, Tokenizer, models, pre_tokenizers

        ranks, chars = read_ranks(path), byte_characters()
        spell = lambda b: "".join(chars[x] for x in b)
        self.model = models.BPE(vocab={spell(t): r for t, r in ranks.items()}, merges=[(spell(a), spell(b)) for a, b in _merges(ranks)], cache_capacity=0)
        self.tokenizer = Tokenizer(self.model)
        self.spelled, self.split = dict(enumerate(chars)), pre_tokenizers.Split(Regex(pattern), "isolated")
        self.tokenizer.pre_tokenizer = pre_tokenizers.Sequence([self.split, pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        self.tokenizer.encode_special_tokens = True
        back = {c: b for b, c in enumerate(chars)}
        self.bytes_of = {i: bytes(back[c] for c in t) for t, i in self.tokenizer.get_vocab().items()}
        self.sizes = np.zeros(max(self.bytes_of) + 1, np.int64)
        self.sizes[list(self.bytes_of)] = [len(x) for x in self.bytes_of.values()]
        #: Per string, int32 triples (id, first character, past-the-last character): of pieces with the space before
        #: them, of words, and of other short strings.
        self.known, self.words, self.strings = Remembered(), Remembered(), Remembered()

    def _word_triples(self, words: list[str]) -> list[bytes]:
        """Triples of matches of the pattern; the model merges those that are new, spelled by the byte table.

        A token's bytes follow from its id, so what it covers is counted in bytes first and then in the characters
        that these bytes begin.
        """
        distinct = list(set(words))
        found = dict(zip(distinct, self.words.get(distinct), strict=True))
        new = [w for w, x in found.items() if x is None]
        if new:
            raw = [w.encode() for w in new]
            ids = [[t.id for t in self.model.tokenize(r.decode("latin-1").translate(self.spelled))] for r in raw]
            data = np.frombuffer(b"".join(raw), np.uint8)
            begun = np.concatenate(([0], np.cumsum(data & 0xC0 != 0x80)))
            n = np.fromiter(map(len, ids), np.int64, len(ids))
            flat = np.fromiter(chain.from_iterable(ids), np.int32, int(n.sum()))
            stop = np.cumsum(self.sizes[flat])
            base = begun[np.cumsum([0, *map(len, raw[:-1])])]
            out = np.empty((len(flat), 3), np.int32)
            out[:, 0] = flat
            out[:, 1] = begun[stop - self.sizes[flat] + 1] - 1 - np.repeat(base, n)
            out[:, 2] = begun[stop] - np.repeat(base, n)
            raw_out, ends = out.tobytes(), (12 * np.cumsum(n)).tolist()
            fresh = dict(zip(new, [raw_out[x:y] for x, y in zip([0, *ends[:-1]], ends, strict=True)], strict=True))
            found.update(fresh)
            self.words.put((w, x) for w, x in fresh.items() if len(w) <= LONGEST_REMEMBERED)
        return list(map(found.__getitem__, words))

    def _split_triples(self, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Triples of a text, and for each match of the pattern its first character and number of tokens."""
        found = self.split.pre_tokenize_str(text)
        got = self._word_triples([w for w, _ in found])
        start = np.fromiter((a for _, (a, _) in found), np.int64, len(found))
        each = np.fromiter(map(len, got), np.int64, len(got)) // 12
        flat = np.frombuffer(b"".join(got), np.int32).reshape(-1, 3).copy()
        flat[:, 1:] += np.repeat(start.astype(np.int32), each)[:, None]
        return flat, start, each

    def _learn(self, pieces: list[str]) -> list[bytes]:
        """Triples of pieces that each follow a space and have no white space at their ends, split by one call."""
        flat, start, each = self._split_triples(" " + " ".join(pieces))
        space = np.cumsum([0, *(len(p) + 1 for p in pieces)])
        ends = np.concatenate(([0], np.cumsum(each)))[np.searchsorted(start, space)]
        flat[:, 1:] -= np.repeat(space[:-1].astype(np.int32), np.diff(ends))[:, None]
        raw, ends = flat.tobytes(), (12 * ends).tolist()
        return [raw[x:y] for x, y in zip(ends[:-1], ends[1:], strict=True)]

    def _one(self, text: str) -> bytes:
        got = self.strings.get([text])[0] if len(text) <= LONGEST_REMEMBERED else None
        if got is None:
            got = self._split_triples(text)[0].tobytes()
            if len(text) <= LONGEST_REMEMBERED:
                self.strings.put([(text, got)])
        return got

    def _whole(self, text: str) -> bytes:
        """Triples of a text with white space of other kinds, piece by piece."""
        head, *rest = CUT.split(text)
        parts, at = [self._one(head)], len(head)
        for p in rest:
            t = np.frombuffer(self.known.new.get(p) or self._one(" " + p), np.int32).reshape(-1, 3) + np.array([0, at, at], np.int32)
            parts.append(t.tobytes())
            at += len(p) + 1
        return b"".join(parts)

    def forget(self) -> None:
        """At the end of a task: the worker may serve other stages next."""
        for held in (self.known, self.words, self.strings):
            held.clear()
        give_back()

    def encode_flat(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(id, first character, past-the-last character) of all texts' tokens, and where each text's end (one more
        entry than texts)."""
        texts = pc.fill_null(texts, "")
        lists = pc.split_pattern(texts, " ")
        first = lists.offsets.to_numpy()
        first = first - first[0]
        coded = pc.dictionary_encode(lists.flatten())
        at, pieces = coded.indices.to_numpy().astype(np.int64), coded.dictionary.to_pylist()
        # the space before a piece stands where the pieces before it, and their spaces, end
        run = np.cumsum(np.array([len(p) + 1 for p in pieces], np.int64)[at]) if len(at) else at
        space = np.concatenate(([0], run[:-1])) if len(at) else at
        space = space - np.repeat(space[first[:-1]], np.diff(first)) - 1
        got = self.known.get(pieces)
        odd = np.zeros(len(pieces), bool)
        missed = []
        for i, x in enumerate(got):
            if x is None:
                p = pieces[i]
                if not p or p[0].isspace() or p[-1].isspace():
                    odd[i], got[i] = True, b""
                else:
                    missed.append(i)
        for k in range(0, len(missed), LEARNED_AT_ONCE):
            part = missed[k : k + LEARNED_AT_ONCE]
            for i, x in zip(part, self._learn([pieces[i] for i in part]), strict=True):
                got[i] = x
        self.known.put((pieces[i], got[i]) for i in missed if len(pieces[i]) <= LONGEST_REMEMBERED)
        # what opens a text has no space before it, and odd pieces are not cut at single spaces: those go one by one
        whole = np.logical_or.reduceat(odd[at], first[:-1]) if len(texts) else np.zeros(0, bool)
        own = [self._whole(texts[d].as_py()) if whole[d] else self._one(pieces[at[first[d]]]) for d in range(len(texts))]
        use = ~np.repeat(whole, np.diff(first))
        use[first[:-1]] = True
        at[first[:-1]] = len(pieces) + np.arange(len(texts))
        space[first[:-1]] = 0
        sizes = np.array([*map(len, got), *map(len, own)], np.int64) // 12
        tokens, begin = np.frombuffer(b"".join([*got, *own]), np.int32).reshape(-1, 3), np.concatenate(([0], np.cumsum(sizes)))
        owner = np.repeat(np.arange(len(texts)), np.diff(first))[use]
        at, space = at[use], space[use].astype(np.int32)
        each = sizes[at]
        end = np.cumsum(each)
        flat = tokens[np.repeat(begin[at] - (end - each), each) + np.arange(end[-1] if len(end) else 0)]
        flat[:, 1:] += np.repeat(space, each)[:, None]
        return flat, np.concatenate(([0], np.cumsum(np.bincount(owner, weights=each, minlength=len(texts))))).astype(np.int64)

    def encode(self, texts: pa.Array | list[str | None]) -> list[list[int]]:
        flat, ends = self.encode_flat(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()))
        return [flat[a:b, 0].tolist() for a, b in zip(ends[:-1], ends[1:], strict=True)]

    def encode_with_offsets(self, texts: pa.Array | list[str | None]) -> list[tuple[list[int], list[int], list[int]]]:
        """Ids with the first and past-the-last character that each covers; a split character counts for each part."""
        flat, ends = self.encode_flat(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()))
        return [tuple(flat[a:b].T.tolist()) for a, b in zip(ends[:-1], ends[1:], strict=True)]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


@lru_cache(maxsize=4)
def codec(path: str, pattern: str | None = None) -> Codec:
    if pattern is None:
        import public_tokenizers

        pattern = public_tokenizers.PATTERN
    return Codec(path, pattern)


def _portions(b: pa.RecordBatch, col: int, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of about that many bytes of text, of one row at least."""
    sizes = pc.fill_null(pc.binary_length(b.column(col)), 0).to_numpy(zero_copy_only=False)
    groups = np.cumsum(sizes) // most
    cuts = [0, *(np.flatnonzero(np.diff(groups)) + 1).tolist(), b.num_rows]
    for x, y in zip(cuts[:-1], cuts[1:], strict=True):
        if y > x:
            yield b.slice(x, y - x)


def _one_thread() -> None:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"


def encode(docs: DataFrame, text_col: str = "text", path: str | None = None, ids_col: str = "ids", offsets: bool = False) -> DataFrame:
    """docs with ids (array<int>), and with offsets also char_start and char_end; null and empty texts give none.

    Columns of these names that docs has are replaced.
    """
    path = path or vocabulary_path()
    added = [ids_col] + (["char_start", "char_end"] if offsets else [])
    base = docs.drop(*added)
    schema = pa.list_(pa.int32())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _one_thread()
        c = codec(path)
        for b in batches:
            for part in _portions(b, b.schema.get_field_index(text_col)):
                texts = [t or "" for t in part.column(part.schema.get_field_index(text_col)).to_pylist()]
                got = c.encode_with_offsets(texts) if offsets else [(x,) for x in c.encode(texts)]
                cols = [[x[k] for x in got] for k in range(len(added))]
                yield pa.RecordBatch.from_arrays([*part.columns, *(pa.array(x, schema) for x in cols)], names=[*part.schema.names, *added])
        c.forget()

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields)
    return bounded_batches(base).mapInArrow(run, fields + "".join(f", `{x}` array<int>" for x in added))


def decode(rows: DataFrame, ids_col: str = "ids", path: str | None = None, to: str = "decoded") -> DataFrame:
    """rows with the decoded bytes (binary); null ids give no bytes."""
    path = path or vocabulary_path()
    base = rows.drop(to)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                got = [c.decode(x or []) for x in part.column(part.schema.get_field_index(ids_col)).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(got, pa.binary())], names=[*part.schema.names, to])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields)
    return base.mapInArrow(run, f"{fields}, `{to}` binary")


@any_names
def round_trip(docs: DataFrame, text_col: str = "text", path: str | None = None) -> DataFrame:
    """docs with ids and n_tokens, and the text that the ids decode to, in one pass; null texts stay null.

    Columns ids and n_tokens that docs has are replaced.
    """
    path = path or vocabulary_path()
    base = docs.drop("ids", "n_tokens")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _one_thread()
        c = codec(path)
        for b in batches:
            k = b.schema.get_field_index(text_col)
            for part in _portions(b, k, 1 << 19):
                old = part.column(k)
                flat, ends = c.encode_flat(old)
                back = [c.decode(flat[x:y, 0].tolist()).decode() if there else None for x, y, there in zip(ends[:-1], ends[1:], old.is_valid().to_pylist(), strict=True)]
                cols = [*part.columns]
                cols[k] = pa.array(back, pa.string())
                yield pa.RecordBatch.from_arrays([*cols, pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.ascontiguousarray(flat[:, 0]))), pa.array(np.diff(ends))], names=[*part.schema.names, "ids", "n_tokens"])
        c.forget()

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields)
    return bounded_batches(base).mapInArrow(run, f"{fields}, ids array<int>, n_tokens bigint")


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """Per row: doc_id, n_tokens, ids_sha256, decoded_sha256 and offsets_sha256, in one pass.

    offsets_sha256 is the digest of the tokens' first and past-the-last characters as little-endian 32-bit numbers.
    """
    path = path or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _one_thread()
        c = codec(path)
        names = list(map(str, range(max(c.bytes_of) + 1)))
        for b in batches:
            for part in _portions(b, 1):
                flat, ends = c.encode_flat(part.column(1))
                out: list[list[str]] = [[], [], []]
                for x, y in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
                    ids = flat[x:y, 0].tolist()
                    for held, raw in zip(out, (" ".join(map(names.__getitem__, ids)).encode(), c.decode(ids), flat[x:y, 1:].astype("<i4").tobytes()), strict=True):
                        held.append(hashlib.sha256(raw).hexdigest())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.diff(ends)), *(pa.array(x, pa.string()) for x in out)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "offsets_sha256"])
        c.forget()

    return bounded_batches(docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))).mapInArrow(run, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string, offsets_sha256 string")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))
