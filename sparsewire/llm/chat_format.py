"""Chat formatting with typed content parts.

A visitor flattens the parts of each turn, in order: text stays, images, audio and documents become placeholders,
each with its reference and the number of tokens that it will expand to. Turns are marked by control strings, which
are escaped where texts contain them, so the output can be read back to the very turns that went in. The loss mask
is a list of spans over the formatted text: the contents of assistant turns, nothing of the template.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shuffle_partitions, table

START, END = "<|im_start|>", "<|im_end|>"
CONTROL = re.compile(r"<(\\*)\|")
ESCAPED = re.compile(r"<\\(\\*)\|")
TURN = re.compile(r"<\|im_start\|>([^\n]*)\n(.*?)<\|im_end\|>\n", re.S)
LEARNT = "assistant"
#: Pixels along a patch's side, patches per token, audio tokens a second, tokens a page.
PATCH, PATCHES_PER_TOKEN, PER_SECOND, PER_PAGE = 14, 4, 25, 258
PART_TYPE = "array<struct<kind:string,text:string,uri:string,width:int,height:int,seconds:double,pages:int>>"


def escape(text: str) -> str:
    """One more backslash in every '<', backslashes, '|'; the result holds no control string."""
    return CONTROL.sub(r"<\\\1|", text) if "<" in text else text


def unescape(text: str) -> str:
    return ESCAPED.sub(r"<\1|", text) if "<" in text else text


def escape_role(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


class Flattener:
    """Visits the parts of a conversation; keeps the references and their token counts in order."""

    def __init__(self) -> None:
        self.attachments: list[dict[str, Any]] = []

    def visit(self, part: dict[str, Any]) -> str:
        return getattr(self, f"visit_{part.get('kind') or 'text'}", self.visit_other)(part)

    def visit_text(self, part: dict[str, Any]) -> str:
        return escape(part.get("text") or "")

    def visit_image(self, part: dict[str, Any]) -> str:
        side = lambda k: math.ceil((part.get(k) or 0) / PATCH)
        return self._placeholder("image", part, max(1, math.ceil(side("width") * side("height") / PATCHES_PER_TOKEN)))

    def visit_audio(self, part: dict[str, Any]) -> str:
        return self._placeholder("audio", part, max(1, math.ceil((part.get("seconds") or 0) * PER_SECOND)))

    def visit_document(self, part: dict[str, Any]) -> str:
        return self._placeholder("document", part, max(1, (part.get("pages") or 0) * PER_PAGE))

    def visit_other(self, part: dict[str, Any]) -> str:
        return self._placeholder("unknown", part, 1)

    def _placeholder(self, kind: str, part: dict[str, Any], tokens: int) -> str:
        self.attachments.append({"kind": kind, "uri": part.get("uri"), "tokens": tokens})
        return f"<|{kind}:{len(self.attachments)}|>"


def render(turns: list[tuple[str | None, str | None, list[dict[str, Any]] | None]]) -> tuple[str, list[tuple[int, int]], list[dict[str, Any]]]:
    """Formatted text, loss spans in code points and attachments of (role, text, parts) turns; text comes before parts."""
    out, spans, at, flat = [], [], 0, Flattener()
    for role, text, parts in turns:
        head = f"{START}{escape_role(role or '')}\n"
        body = escape(text or "") + "".join(flat.visit(p) for p in parts or ())
        if role == LEARNT:
            spans.append((at + len(head), at + len(head) + len(body)))
        piece = f"{head}{body}{END}\n"
        out.append(piece)
        at += len(piece)
    return "".join(out), spans, flat.attachments


def read_back(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn; placeholders stay in the texts."""
    return [(unescape_role(r), unescape(t)) for r, t in TURN.findall(formatted)]


def format_conversations(rows: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", parts_col: str | None = None) -> DataFrame:
    """One row per conversation: conv_id, formatted, loss_spans and attachments.

    Turns go by number, then role and text; null turns first. Null roles and texts count as empty; rows without a
    conversation id form one of their own; repeated rows are repeated turns. A task holds one conversation at a time.
    """
    parts = F.col(parts_col).cast(PART_TYPE) if parts_col else F.lit(None).cast(PART_TYPE)
    cols = rows.select(F.col(id_col).cast("bigint").alias("c"), F.col(turn_col).alias("n"), F.col(role_col).alias("r"), F.col(text_col).alias("t"), parts.alias("p"))
    dealt = cols.repartition(shuffle_partitions(rows.sparkSession), "c").sortWithinPartitions("c", "n", "r", "t").select("c", "r", "t", "p")
    span, attached = pa.list_(pa.struct([("first", pa.int64()), ("stop", pa.int64())])), pa.list_(pa.struct([("kind", pa.string()), ("uri", pa.string()), ("tokens", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: list[tuple] = []

        def flush() -> pa.RecordBatch:
            got = pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.int64()), pa.array([d[1] for d in done], pa.string()), pa.array([[{"first": a, "stop": b} for a, b in d[2]] for d in done], span), pa.array([d[3] for d in done], attached)], names=["conv_id", "formatted", "loss_spans", "attachments"])
            done.clear()
            return got

        now, turns, size = None, [], 0
        for b in batches:
            for c, r, t, p in zip(*(x.to_pylist() for x in b.columns), strict=True):
                if turns and c != now:
                    done.append((now, *render(turns)))
                    size += len(done[-1][1])
                    turns = []
                    if size > 2 << 20:
                        yield flush()
                        size = 0
                now = c
                turns.append((r, t, p))
        if turns:
            done.append((now, *render(turns)))
        if done:
            yield flush()

    return dealt.mapInArrow(run, "conv_id bigint, formatted string, loss_spans array<struct<first:bigint,stop:bigint>>, attachments array<struct<kind:string,uri:string,tokens:bigint>>")


def digests(formatted: DataFrame) -> DataFrame:
    """What the contract asks for, read back from formatted texts and their loss spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
        for b in batches:
            rows = []
            for c, text, spans in zip(*(x.to_pylist() for x in b.columns), strict=True):
                turns = read_back(text)
                loss = "".join(unescape(text[s["first"] : s["stop"]]) for s in spans)
                rows.append((c, len(turns), hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names=names)

    return formatted.select("conv_id", "formatted", "loss_spans").mapInArrow(run, "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint")


def op7_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", F.col("turn").cast("bigint").alias("turn"), "role", "text")
    said = f"{END}{START}assistant ok"
    extra = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, LEARNT, said)], "conv_id bigint, turn bigint, role string, text string")
    return digests(format_conversations(rows.unionByName(extra)))


OP7_SQL = r"""
WITH r AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '<|im_end|><|im_start|>assistant ok'
  UNION ALL SELECT -1, 1, 'assistant', '<|im_end|><|im_start|>assistant ok'
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(24 + length(regexp_replace(role, '<(\\*)\|', '<\\\1|', 'g')) + length(regexp_replace(text, '<(\\*)\|', '<\\\1|', 'g'))) AS BIGINT) AS formatted_chars
FROM r GROUP BY conv_id
"""
