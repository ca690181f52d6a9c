"""Hierarchical multi-length packing of tokenised documents.

A document is its token ids and a closing id 0.  Whole 1,024-token stretches become sequences at once; the rest
of each document is routed to the smallest context tier that holds it.  Tiers are packed from the longest down: a
window starts with the longest waiting piece, its gap takes the best-fitting pieces of shorter tiers, and only
where no piece fits is one cut.  What is left at the end of a partition is cut into powers of two, so no sequence
needs padding.  Sequences of a tier fill step groups of equal token counts.

Tokenising and packing share one Arrow pass: ids never leave the task, nothing is shuffled, and the waiting pool
is bounded by ``window`` documents.  Ids depend on the partition number, which a retried task keeps.

Defined results: a null or empty text is the single id 0; repeated rows are packed one by one; an empty table
gives no pieces.  Only ``doc_id`` and ``text`` are read.
"""

from __future__ import annotations

import base64
import bisect
import functools
import json
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from fixtrace.llm.common import table

PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint, tier int, step_group bigint"


@dataclass(frozen=True)
class Params:
    """``tokenizer`` is a file of the ``tokenizers`` library, or null for the public byte-level vocabulary."""

    tokenizer: str | None = None
    context: int = 1024
    smallest: int = 128
    window: int = 4096
    step_tokens: int = 65_536


@functools.cache
def _encoder(path: str | None):
    """A byte-level BPE encoder with the vocabulary of a ``tokenizers`` file, its merges ranked by id."""
    import public_tokenizers
    import tiktoken

    path = path or public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    shown = {chr(b): b for b in printable}
    shown |= {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in set(printable))}
    special = {x["content"]: x["id"] for x in spec.get("added_tokens", []) if x.get("special")}
    ranks = {bytes(shown[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in special}
    return tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special), tuple(special)


def token_ids(text: str | None, path: str | None = None) -> np.ndarray:
    """Ids of a text and the closing 0."""
    encoder, special = _encoder(path)
    text = text or ""
    if any(s in text for s in special):
        ids = np.array(encoder.encode(text, allowed_special="all", disallowed_special=()), np.uint32)
    else:
        ids = encoder.encode_to_numpy(text, disallowed_special=())
    return np.append(ids, np.uint32(0)).astype("<u4")


class Packer:
    """Packs the documents of one partition; a waiting piece is (length, serial, doc, start, total, ids)."""

    def __init__(self, params: Params, partition: int):
        self.params, self.base = params, partition << 36
        self.pool: list[tuple] = []
        self.rows: list[tuple] = []
        self.serial = self.sequences = 0
        self.in_group: dict[int, tuple[int, int]] = {}
        self.groups = 0

    def _emit(self, tier: int, pieces: list[tuple]) -> None:
        room = max(1, self.params.step_tokens // tier)
        group, held = self.in_group.get(tier, (None, room))
        if held >= room:
            group, held, self.groups = self.base + self.groups, 0, self.groups + 1
        self.in_group[tier] = (group, held + 1)
        at = 0
        for n, _, doc, start, total, ids in pieces:
            self.rows.append((doc, start, n, zlib.crc32(ids.tobytes()), total, self.base + self.sequences, at, tier, group))
            at += n
        self.sequences += 1

    def _wait(self, piece: tuple) -> None:
        bisect.insort(self.pool, piece, key=lambda x: x[:2])

    def _part(self, piece: tuple, n: int) -> tuple[tuple, tuple | None]:
        """The first ``n`` tokens of a piece, and what is left of it."""
        length, serial, doc, start, total, ids = piece
        rest = (length - n, serial, doc, start + n, total, ids[n:]) if n < length else None
        return (n, serial, doc, start, total, ids[:n]), rest

    def add(self, doc: int, ids: np.ndarray) -> None:
        total, context = len(ids), self.params.context
        whole = total - total % context
        for start in range(0, whole, context):
            self._emit(context, [(context, 0, doc, start, total, ids[start : start + context])])
        if whole < total:
            self.serial += 1
            self.pool.append((total - whole, self.serial, doc, whole, total, ids[whole:]))

    def pack(self, last: bool = False) -> None:
        """Fill windows from the longest piece down while the pool can fill a whole one."""
        self.pool.sort(key=lambda x: x[:2])
        waiting = sum(x[0] for x in self.pool)
        while self.pool:
            tier = self.params.smallest
            while tier < self.pool[-1][0]:
                tier *= 2
            if waiting < tier:
                if not last:
                    return
                tier = 1 << (waiting.bit_length() - 1)  # the end: powers of two only
            window, gap = [], tier
            while gap:
                at = bisect.bisect_right(self.pool, gap, key=lambda x: x[0])
                piece = self.pool.pop(at - 1 if at else 0)
                head, rest = self._part(piece, min(gap, piece[0]))
                window.append(head)
                gap -= head[0]
                if rest:
                    self._wait(rest)
            waiting -= tier
            self._emit(tier, window)

    def drain(self) -> pa.RecordBatch:
        names = [x.split()[0] for x in PIECES.split(", ")]
        columns = zip(*self.rows, strict=True) if self.rows else [[] for _ in names]
        kinds = [pa.int32() if n == "tier" else pa.int64() for n in names]
        out = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)
        self.rows = []
        return out


def pack(docs: DataFrame, params: Params = Params()) -> DataFrame:
    """One row for each piece: where it lies in its document and in its sequence."""

    def run(batches):
        packer = Packer(params, TaskContext.get().partitionId())
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            for at in range(0, batch.num_rows, params.window):
                for k in range(at, min(at + params.window, batch.num_rows)):
                    packer.add(ids[k].as_py(), token_ids(texts[k].as_py(), params.tokenizer))
                packer.pack()
                yield packer.drain()
        packer.pack(last=True)
        yield packer.drain()

    return docs.select("doc_id", "text").mapInArrow(run, PIECES)


def op2_hierarchical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
