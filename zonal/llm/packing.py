"""Hierarchical multi-length packing of tokenised documents.

Each document's ids (its text's ids, then one end id) are cut into full windows of the
longest tier; the rest is routed to the shortest tier that holds it. Tiers are packed from
long to short: a window opens with the tier's largest rest, its gap is filled with the
largest shorter rests that fit, and the last hole by cutting one more rest, so windows come
out exactly full and need no padding. Only what an input split can't fill at its end is
written in full shorter tiers and one padded sequence. Full windows of a tier are dealt into
step groups of equal token counts.

All of it is local to an input split: no exchange, memory for one Arrow batch. Sequence ids
carry the split's number, so a task run again after a lost executor writes the same ids.

The ids are those of the byte-level BPE of ``byte_bpe_50k.json``, its added token included;
they are computed from the same vocabulary's rank file, several times faster, which a test
holds against the JSON.

Defined results: null text is empty; an empty document is its end id alone; repeated rows
are packed each; an empty table has no sequences.
"""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

TIERS = (256, 512, 1024, 2048)
END_ID = 1
#: Tokens in a step group; each tier fills a group with windows of its own length.
STEP_TOKENS = 131_072

_ENCODERS: dict[str, Callable[[str], list[int]]] = {}


def encoder(name: str) -> Callable[[str], list[int]]:
    """text to ids; one encoder a worker process."""
    if name not in _ENCODERS:
        import base64
        import json

        import public_tokenizers
        import tiktoken

        with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        with open(public_tokenizers.path(f"{name}.json"), encoding="utf-8") as f:
            added = {t["content"]: t["id"] for t in json.load(f)["added_tokens"]}
        bpe = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=added)
        _ENCODERS[name] = lambda text: bpe.encode(text, allowed_special="all")
    return _ENCODERS[name]


class Packer:
    """Packs rests of documents: ``add`` and ``pack`` any number of times, then ``finish``."""

    def __init__(self, tiers: tuple[int, ...] = TIERS):
        self.tiers = tuple(sorted(tiers))
        self.rests: list[tuple[int, int, int]] = []  # (length, document, start), sorted
        self.out: list[tuple[int, list[tuple[int, int, int]]]] = []  # (tier, [(document, start, length)])

    def add(self, doc: int, n: int) -> None:
        top, at = self.tiers[-1], 0
        while n - at >= top:
            self.out.append((top, [(doc, at, top)]))
            at += top
        if at < n:
            bisect.insort(self.rests, (n - at, doc, at))

    def _fill(self, gap: int) -> tuple[list[tuple[int, int, int]], int]:
        """Pieces for a gap: best fits first, then one cut."""
        pieces, rests = [], self.rests
        while gap and rests:
            i = bisect.bisect_right(rests, (gap, float("inf"), 0)) - 1
            if i >= 0:
                n, doc, at = rests.pop(i)
                pieces.append((doc, at, n))
                gap -= n
            else:
                n, doc, at = rests.pop(0)
                pieces.append((doc, at, gap))
                bisect.insort(rests, (n - gap, doc, at + gap))
                gap = 0
        return pieces, gap

    def pack(self, floor: int) -> None:
        """Full windows, as long as ``floor`` tokens are left over."""
        left = sum(r[0] for r in self.rests)
        for tier in reversed(self.tiers):
            while left - tier >= floor and self.rests and self.rests[-1][0] * 2 > tier:
                n, doc, at = self.rests.pop()
                head = (doc, at, min(n, tier))
                if n > tier:
                    bisect.insort(self.rests, (n - tier, doc, at + tier))
                pieces, _ = self._fill(tier - head[2])
                self.out.append((tier, [head, *pieces]))
                left -= tier
        low = self.tiers[0]
        while left - low >= floor:
            pieces, _ = self._fill(low)
            self.out.append((low, pieces))
            left -= low

    def finish(self) -> None:
        self.pack(0)
        if self.rests:  # less than the shortest tier: the split's only padded sequence
            self.out.append((self.tiers[-1], [(doc, at, n) for n, doc, at in self.rests]))
            self.rests = []


def pack(
    docs: DataFrame,
    vocabulary: str = "byte_bpe_50k",
    tiers: tuple[int, ...] = TIERS,
    end_id: int = END_ID,
    step_tokens: int = STEP_TOKENS,
    with_ids: bool = False,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset,
    tier (the padded length), step_group and, if asked for, ids (32-bit little-endian)."""
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "tier", "step_group"]
    schema = ", ".join(f"{n} bigint" for n in names) + (", ids binary" if with_ids else "")
    kinds = pa.schema([(n, pa.int64()) for n in names] + ([("ids", pa.binary())] if with_ids else []))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base, encode, packer = TaskContext.get().partitionId() << 32, encoder(vocabulary), Packer(tiers)
        held: dict[int, tuple[int | None, np.ndarray]] = {}
        made = dict.fromkeys(tiers, 0)
        sequence = number = 0

        def flush() -> pa.RecordBatch:
            nonlocal sequence
            rows: list[tuple] = []
            for tier, pieces in packer.out:
                group = made[tier] // max(1, step_tokens // tier)
                made[tier] += 1
                offset = 0
                for doc, at, n in pieces:
                    doc_id, ids = held[doc]
                    part = ids[at : at + n].tobytes()
                    row = (doc_id, at, n, zlib.crc32(part), len(ids), base + sequence, offset, tier, base + group * len(tiers) + tiers.index(tier))
                    rows.append((*row, part) if with_ids else row)
                    offset += n
                sequence += 1
            packer.out = []
            open_docs = {r[1] for r in packer.rests}
            for doc in [d for d in held if d not in open_docs]:
                del held[doc]
            return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows) if rows else [[] for _ in kinds], kinds, strict=True)], schema=kinds)

        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.array([*encode(text.as_py()), end_id], dtype="<u4")
                held[number] = doc_id, ids
                packer.add(number, len(ids))
                number += 1
                if number % 2000 == 0:
                    packer.pack(4 * tiers[-1])
                    yield flush()
        packer.finish()
        yield flush()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text")).mapInArrow(run, schema)
