"""Removal of repeated byte strings by suffix sorting.

A byte goes when it is covered by a string of ``length`` bytes that also starts in a document
with a smaller id. Three written passes lead from all texts to the few that need sorting:

1. Equal texts are grouped (a partial aggregation); only the smallest id's text goes on, the
   others are repeats as a whole.
2. The smallest hash of the short grams inside a window of ``length`` bytes belongs to the
   window's content alone. Consecutive windows with one smallest hash form a run; a run whose
   hash occurs in one document only holds no repeat. Tasks send the runs' hashes to buckets,
   once for some megabytes of text, and hear which of them several documents have.
3. Those runs' bytes go to their hash's bucket. Equal runs merge into one with the smallest
   id. Where runs of one hash differ, the stretches of them whose windows may occur in
   another are kept and merged likewise; the suffixes of those that still differ are sorted,
   neighbours of at least ``length`` equal bytes form groups, and each group's smallest id
   decides over its windows.

Suffixes are sorted by linear grouping: suffixes fall into groups by first byte; from the
largest group down, each group's Lyndon prefix extends the groups of the positions before it,
found over previous-smaller pointers, so that groups come to hold equal longest Lyndon
prefixes; one pass upwards then writes every group's order, from each suffix to the ones
before it, without renaming anything.

Hashes only propose; bytes decide. Rows between passes are compressed columns by bucket; a
passage that thousands of documents share is one string there. The passes' tables lie in the
shared folder, so lost executors cost a re-read.

Defined results: null text is empty; texts below ``length`` bytes lose nothing; rows with
equal ids never remove from each other, repeated rows are one document; null ids take no part
and keep everything; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import buckets_for, materialize, shared_path, text_or_empty

U = np.uint64
GRAM, PIECE, FLUSH = 18, 1 << 20, 12 << 20
#: Bytes of differing runs that are sorted in one go.
SORT_BYTES = 1 << 17
_CODES = np.random.default_rng(77).integers(1, 1 << 63, 256, dtype=U) * U(2) + U(1)
_MUL = U(0xD6E8FEB86659FD93)


# ---- suffix sorting ------------------------------------------------------------------------


def suffix_order(text: list[int]) -> list[int]:
    """Suffix array of a list of positive numbers, by linear Lyndon grouping."""
    n = len(text) + 1
    t = [*text, 0]
    top = max(t) + 1
    fill = [0] * (top + 1)
    for c in t:
        fill[c + 1] += 1
    for c in range(top):
        fill[c + 1] += fill[c]
    group = [fill[c] for c in t]  # a group is named by its first slot
    slot, size, order = [0] * n, [0] * n, [0] * n
    for i, g in enumerate(group):
        at = g + size[g]
        order[at], slot[i] = i, at
        size[g] += 1
    smaller = [-1] * n
    end = n
    while end:
        first = group[order[end - 1]]
        members = order[first:end]
        heads = []
        if len(members) == 1:
            i = members[0]
            p = i - 1
            while p >= 0 and group[p] > first:
                p = smaller[p]
            smaller[i] = p
            if p >= 0:
                g = group[p]
                left = size[g] - 1
                size[g] = left
                to, at = g + left, slot[p]
                if to != at:
                    q = order[to]
                    order[at], slot[q] = q, at
                    order[to], slot[p] = p, to
                group[p] = to
                size[to] = 1 if left else left + 1
            end = first
            continue
        runs = dict.fromkeys(members, 1)
        members.sort(reverse=True)
        for i in members:
            p = i - 1
            while p >= 0 and group[p] > first:
                p = smaller[p]
            smaller[i] = p
            if p >= 0:
                if group[p] == first:
                    runs[p] = runs[i] + 1
                else:
                    heads.append((runs[i], p))
        for i in reversed(members):  # a repetition's own pointer leads out of its group
            p = smaller[i]
            if p >= 0 and group[p] == first:
                smaller[i] = smaller[p]
        at = 0
        heads.sort(reverse=True)
        while at < len(heads):  # most repetitions first: they go to their group's very end
            k, upto = heads[at][0], at
            while upto < len(heads) and heads[upto][0] == k:
                p = heads[upto][1]
                g = group[p]
                left = size[g] - 1
                size[g] = left
                to, here = g + left, slot[p]
                if to != here:
                    q = order[to]
                    order[here], slot[q] = q, here
                    order[to], slot[p] = p, to
                upto += 1
            moved = [(p, group[p]) for _, p in heads[at:upto]]
            fresh = [(p, g + size[g]) for p, g in moved]
            for p, new in fresh:
                group[p] = new
                size[new] = 0
            for _, new in fresh:
                size[new] += 1
            at = upto
        end = first
    # upwards: the next slot of a group goes to the suffix in front of the one just read
    written = [False] * n
    free = list(range(n))
    out = [0] * n
    out[0] = n - 1
    written[n - 1] = True
    for i in range(n):
        j = out[i] - 1
        while j >= 0 and not written[j]:
            g = group[j]
            out[free[g]] = j
            free[g] += 1
            written[j] = True
            j = smaller[j]
    return out[1:]


def window_groups(strings: list[bytes], owner: np.ndarray, length: int) -> list[np.ndarray]:
    """For every window of ``length`` bytes of every string the smallest owner it occurs with."""
    sizes = np.array([len(s) for s in strings])
    starts = np.concatenate([[0], np.cumsum(sizes + 1)[:-1]])
    raw = np.frombuffer(b"\0".join(strings) + b"\0" * (length + 1), np.uint8).astype(np.int16) + 2
    total = int(starts[-1] + sizes[-1])
    ends = starts + sizes
    raw[ends] = 1
    raw[total:] = 1
    order = np.array(suffix_order(raw[:total].tolist()), np.int64)
    which = np.searchsorted(starts, order, side="right") - 1
    whole = order + length <= ends[which]
    order, which = order[whole], which[whole]
    offsets = np.arange(length)
    same = np.zeros(len(order), bool)
    for i in range(1, len(order), 1 << 14):
        a, b = order[i - 1 : i - 1 + (1 << 14)], order[i : i + (1 << 14)]
        a = a[: len(b)]
        same[i : i + len(b)] = (raw[a[:, None] + offsets] == raw[b[:, None] + offsets]).all(axis=1)
    first = np.flatnonzero(~same)
    least = np.minimum.reduceat(owner[which], first)
    by_place = np.zeros(total, owner.dtype)
    by_place[order] = np.repeat(least, np.diff(np.append(first, len(order))))
    return [by_place[s : s + n - length + 1] for s, n in zip(starts.tolist(), sizes.tolist(), strict=True)]


def shared_windows(strings: list[bytes], owner: np.ndarray, family: np.ndarray, length: int) -> list[np.ndarray | None]:
    """For every string the smallest owner of each of its windows; None where that is its own.

    Only strings of one family (neighbours in the list) can share windows. A window whose
    hash occurs once is shared with nobody; what is left are stretches of the strings, equal
    ones merge, and families with several different stretches are suffix-sorted.
    """
    out: list[np.ndarray | None] = [None] * len(strings)
    if not strings:
        return out
    sizes = np.array([len(s) for s in strings])
    begins = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    h = gram_hashes(np.frombuffer(b"".join(strings), np.uint8), length)
    which = np.repeat(np.arange(len(strings)), sizes)[: len(h)]
    inside = np.arange(len(h)) + length <= (begins + sizes)[which]
    place, which = np.flatnonzero(inside), which[inside]
    h = h[place] ^ (family[which] * _MUL)
    order = np.argsort(h)
    same = h[order][1:] == h[order][:-1]
    often = np.zeros(len(h), bool)
    often[order[1:][same]] = True
    often[order[:-1][same]] = True
    place, which = place[often], which[often]
    if not len(place):
        return out
    cut = np.flatnonzero(np.concatenate([[True], (place[1:] != place[:-1] + 1) | (which[1:] != which[:-1]), [True]]))
    number: dict[tuple[int, bytes], int] = {}
    least: list[int] = []
    stretches = []
    for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
        k = int(which[a])
        at, n = int(place[a] - begins[k]), b - a
        key = (int(family[k]), strings[k][at : at + n + length - 1])
        i = number.setdefault(key, len(least))
        if i == len(least):
            least.append(int(owner[k]))
        else:
            least[i] = min(least[i], int(owner[k]))
        stretches.append((k, at, n, i))
    least_of = np.array(least)
    families: dict[int, list[int]] = {}
    for i, (f, _) in enumerate(number):
        families.setdefault(f, []).append(i)
    pieces = [piece for _, piece in number]
    windows: dict[int, np.ndarray] = {}
    batch: list[int] = []
    size = 0
    for group in [*families.values(), []]:
        if size >= SORT_BYTES or (not group and batch):
            windows |= zip(batch, window_groups([pieces[i] for i in batch], least_of[batch], length), strict=True)
            batch, size = [], 0
        if len(group) > 1:
            batch += group
            size += sum(len(pieces[i]) for i in group)
    for k, at, n, i in stretches:
        found = windows[i] if i in windows else np.full(n, least_of[i])
        if (found < owner[k]).any():
            if out[k] is None:
                out[k] = np.full(len(strings[k]) - length + 1, owner[k])
            out[k][at : at + n] = found
    return out


# ---- runs of windows with one smallest hash ------------------------------------------------


def gram_hashes(x: np.ndarray, gram: int) -> np.ndarray:
    """A 48-bit hash of the ``gram`` bytes from each place on."""
    h, span, power = _CODES[x], 1, int(_MUL)
    done, at, whole = None, 0, gram
    while True:  # doubling: hashes of 1, 2, 4, ... bytes make up any length
        if whole & span:
            if done is None:
                done, at = h, span
            else:
                n = len(x) - at - span + 1
                done, at = done[:n] * U(power) + h[at : at + n], at + span
        if span * 2 > whole:
            break
        n = len(h) - span
        h = h[:n] * U(power) + h[span:]
        span, power = span * 2, power * power & 0xFFFFFFFFFFFFFFFF
    v = done
    v = (v ^ (v >> U(31))) * U(0x7FB5D329728EA185)
    v = (v ^ (v >> U(27))) * U(0x81DADEF4BC2DD44D)
    return v >> U(16)


def least_hashes(x: np.ndarray, length: int, gram: int = GRAM) -> np.ndarray:
    """For each window of ``length`` bytes the smallest hash of its grams."""
    v = gram_hashes(x, gram)
    wide, span = length - gram + 1, 1
    while span * 2 <= wide:
        v = np.minimum(v[:-span], v[span:])
        span *= 2
    rest = wide - span
    return np.minimum(v[: len(v) - rest], v[rest:]) if rest else v


def runs_of(texts: list[bytes], length: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(text number, first window, windows, hash) of all runs, in pieces of bounded size."""
    held, size = [], 0

    def settle() -> tuple[np.ndarray, ...]:
        joined = np.frombuffer(b"".join(p for _, _, p in held), np.uint8)
        v = least_hashes(joined, length)
        sizes = np.array([len(p) for _, _, p in held])
        begins = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        new = np.ones(len(v), bool)
        new[1:] = v[1:] != v[:-1]
        new[begins[begins < len(v)]] = True
        past = begins + sizes - length + 1  # windows from here on reach into the next text
        new[past[past < len(v)]] = True
        at = np.flatnonzero(new)
        n = np.diff(np.append(at, len(v)))
        piece = np.searchsorted(begins, at, side="right") - 1
        ok = at < past[piece]
        at, n, piece = at[ok], n[ok], piece[ok]
        number = np.array([i for i, _, _ in held])[piece]
        offset = np.array([o for _, o, _ in held])[piece] + at - begins[piece]
        return number, offset, n, v[at]

    for i, text in enumerate(texts):
        if len(text) < length:
            continue
        for o in range(0, len(text) - length + 1, PIECE):
            piece = text[o : o + PIECE + length - 1]
            held.append((i, o, piece))
            size += len(piece)
            if size >= PIECE:
                yield settle()
                held, size = [], 0
    if held:
        yield settle()


# ---- compressed columns between the passes --------------------------------------------------


def _pack(*arrays: np.ndarray | bytes) -> bytes:
    parts = [a if isinstance(a, bytes) else np.ascontiguousarray(a).tobytes() for a in arrays]
    head = np.array([len(p) for p in parts], "<i8").tobytes()
    body = head + b"".join(parts)
    return len(body).to_bytes(8, "little") + pa.Codec("zstd", 1).compress(body, asbytes=True)


def _unpack(payload: bytes, *kinds: str | None) -> list:
    body = pa.Codec("zstd").decompress(payload[8:], int.from_bytes(payload[:8], "little"), asbytes=True)
    sizes, at, out = np.frombuffer(body, "<i8", len(kinds)), 8 * len(kinds), []
    for n, kind in zip(sizes.tolist(), kinds, strict=True):
        part = body[at : at + n]
        out.append(part if kind is None else np.frombuffer(part, kind))
        at += n
    return out


def _rows(rows: list[tuple[int, bytes]], name: str) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], [name, "payload"])


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[bytes]]]:
    """(key, payloads) of rows sorted by key."""
    now, held = None, []
    for batch in batches:
        for key, payload in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            if held and key != now:
                yield now, held
                held = []
            now = key
            held.append(payload.as_py())
    if held:
        yield now, held


def _by(values: np.ndarray, n: int) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(values, kind="stable")
    cuts = np.searchsorted(values[order], np.arange(n + 1))
    for b in np.flatnonzero(np.diff(cuts)).tolist():
        yield b, order[cuts[b] : cuts[b + 1]]


def _texts_by_pid(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray, list[bytes]]]:
    """(pid, numbers, ids, texts) in portions of bounded size; the table has doc_id, text, pid, num."""
    for batch in batches:
        if not batch.num_rows:
            continue
        pids = batch.column(2).to_numpy(zero_copy_only=False)
        ids, texts = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).cast(pa.binary())
        nums = batch.column(3).to_numpy(zero_copy_only=False)
        sizes = np.cumsum(np.diff(np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)))
        part = np.concatenate([[0], np.flatnonzero((pids[1:] != pids[:-1]) | (sizes[1:] // FLUSH != sizes[:-1] // FLUSH)) + 1, [len(pids)]])
        for a, b in zip(part[:-1].tolist(), part[1:].tolist(), strict=True):
            yield int(pids[a]), nums[a:b], ids[a:b], texts.slice(a, b - a).to_pylist()


class _Told:
    """Payloads that an earlier pass left for a pid, read when the pid is first met."""

    def __init__(self, path: str):
        self.path, self.pid, self.got = path, None, []

    def of(self, pid: int) -> list[bytes]:
        if self.pid != pid:
            import pyarrow.parquet as pq
            from pyarrow import fs

            store, root = fs.FileSystem.from_uri(self.path)
            where = f"{root}/pid={pid}"
            self.pid, self.got = pid, []
            if store.get_file_info(where).type == fs.FileType.Directory:
                for info in store.get_file_info(fs.FileSelector(where)):
                    if info.base_name.endswith(".parquet"):
                        self.got += pq.ParquetFile(store.open_input_file(info.path)).read(["payload"]).column(0).to_pylist()
        return self.got


# ---- the passes -----------------------------------------------------------------------------


def removed_intervals(texts: DataFrame, length: int, buckets: int) -> str:
    """Path of a table (pid, payload: numbers, starts, ends of removed stretches) for a written
    table (doc_id, text, pid, num) of distinct texts; num tells texts apart, ids need not."""
    spark = texts.sparkSession

    def send_hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for pid, _, _, bodies in _texts_by_pid(batches):
            pairs = [(who, v) for who, _, _, v in runs_of(bodies, length)]
            if not pairs:
                continue
            number, v = (np.concatenate(x) for x in zip(*pairs, strict=True))
            # a hash once a portion, and whether several of its texts have it
            by_text = np.unique(v ^ (number.astype(U) * _MUL), return_index=True)[1]
            v, times = np.unique(v[by_text], return_counts=True)
            yield _rows([(b, _pack(np.array([pid]), v[at], times[at] > 1)) for b, at in _by((v % U(buckets)).astype(np.int64), buckets)], "bucket")

    def find_shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, payloads in _grouped(batches):
            got = [_unpack(p, "<i8", "<u8", "?") for p in payloads]
            v, many = np.concatenate([x for _, x, _ in got]), np.concatenate([x for _, _, x in got])
            pids = np.repeat([int(pid[0]) for pid, _, _ in got], [len(x) for _, x, _ in got])
            order = np.argsort(v, kind="stable")
            s = v[order]
            first = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
            n = np.diff(np.append(first, len(s)))
            at = order[np.repeat((n > 1) | np.logical_or.reduceat(many[order], first), n)]
            at = at[np.argsort(pids[at], kind="stable")]
            cuts = np.flatnonzero(np.concatenate([[True], pids[at][1:] != pids[at][:-1], [True]])) if len(at) else []
            yield _rows([(int(pids[at[a]]), _pack(v[at[a:b]])) for a, b in zip(cuts[:-1], cuts[1:], strict=True)], "pid")

    def passed(rows: DataFrame, to: str) -> str:
        path = shared_path(spark, to)
        rows.write.partitionBy("pid").parquet(path)
        return path

    hashes = texts.mapInArrow(send_hashes, "bucket int, payload binary")
    shared = hashes.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(find_shared, "pid int, payload binary")
    told_path = passed(shared.repartition("pid"), "suffix-shared")

    def send_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told, known_pid, shared = _Told(told_path), None, np.empty(0, U)
        for pid, nums, ids, bodies in _texts_by_pid(batches):
            if pid != known_pid:
                known_pid = pid
                shared = np.unique(np.concatenate([np.empty(0, U), *(_unpack(p, "<u8")[0] for p in told.of(pid))]))
            if not len(shared):
                continue
            found = []
            for who, at, n, v in runs_of(bodies, length):
                hit = shared[np.minimum(np.searchsorted(shared, v), len(shared) - 1)] == v
                found.append((who[hit], at[hit], n[hit], v[hit]))
            if not found:
                continue
            who, at, n, v = (np.concatenate(x) for x in zip(*found, strict=True))
            rows = []
            for b, pick in _by((v % U(buckets)).astype(np.int64), buckets):
                body = b"".join(bodies[w][a : a + k + length - 1] for w, a, k in zip(who[pick].tolist(), at[pick].tolist(), n[pick].tolist(), strict=True))
                rows.append((b, _pack(np.array([pid]), v[pick], nums[who[pick]], ids[who[pick]], at[pick].astype("<i8"), n[pick].astype("<i8"), body)))
            yield _rows(rows, "bucket")

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, payloads in _grouped(batches):
            # distinct strings of the bucket, with their hash and the smallest id that has them
            number: dict[tuple[int, bytes], int] = {}
            least: list[int] = []
            seen = []
            for p in payloads:
                pid, v, nums, ids, at, n, body = _unpack(p, "<i8", "<u8", "<i8", "<i8", "<i8", "<i8", None)
                which, place = np.empty(len(v), np.int64), 0
                for i, (h, d, size) in enumerate(zip(v.tolist(), ids.tolist(), (n + length - 1).tolist(), strict=True)):
                    key = (h, body[place : place + size])
                    place += size
                    k = number.setdefault(key, len(least))
                    if k == len(least):
                        least.append(d)
                    elif d < least[k]:
                        least[k] = d
                    which[i] = k
                seen.append((int(pid[0]), nums, ids, at, n, which))
            strings = [s for _, s in number]
            owner = np.array(least)
            by_hash: dict[int, list[int]] = {}
            for k, (h, _) in enumerate(number):
                by_hash.setdefault(h, []).append(k)
            del number
            mixed = [k for group in by_hash.values() if len(group) > 1 for k in group]
            decided = shared_windows([strings[k] for k in mixed], owner[mixed], np.array([h for h, group in by_hash.items() if len(group) > 1 for _ in group], U), length)
            decided = {k: w for k, w in zip(mixed, decided, strict=True) if w is not None}
            for pid, nums, ids, at, n, which in seen:
                plain = (owner[which] < ids)
                special = np.array([k in decided for k in which.tolist()], bool)
                out_nums, starts, ends = [nums[plain & ~special]], [at[plain & ~special]], [(at + n)[plain & ~special] + length - 1]
                for i in np.flatnonzero(special).tolist():
                    gone = np.concatenate([[False], decided[int(which[i])] < ids[i], [False]])
                    edge = np.flatnonzero(gone[1:] != gone[:-1])
                    begin, end = edge[::2], edge[1::2]
                    out_nums.append(np.full(len(begin), nums[i]))
                    starts.append(at[i] + begin)
                    ends.append(at[i] + end + length - 1)
                out_nums, starts, ends = np.concatenate(out_nums), np.concatenate(starts), np.concatenate(ends)
                if len(out_nums):
                    o = np.lexsort((starts, out_nums))
                    yield _rows([(pid, _pack(out_nums[o], starts[o].astype("<i8"), ends[o].astype("<i8")))], "pid")

    runs = texts.mapInArrow(send_runs, "bucket int, payload binary")
    gone = runs.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(decide, "pid int, payload binary")
    return passed(gone.repartition("pid"), "suffix-gone")


def merged(starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of overlapping or touching stretches, given in order of start."""
    if not len(starts):
        return starts, ends
    reach = np.maximum.accumulate(ends)
    new = np.concatenate([[True], starts[1:] > reach[:-1]])
    first = np.flatnonzero(new)
    return starts[first], reach[np.append(first[1:], len(starts)) - 1]


def remove_repeats(docs: DataFrame, length: int = 50, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if asked for, the kept bytes and
    the removed spans ``array<struct<start, end>>``; one row per row of ``docs``."""
    if length <= GRAM:
        raise ValueError(f"length must be above {GRAM}")
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    reps = rows.where(F.col("doc_id").isNotNull()).groupBy("text").agg(F.min("doc_id").alias("doc_id"))
    texts = materialize(reps.select("doc_id", "text", F.spark_partition_id().alias("pid"), F.monotonically_increasing_id().alias("num")), "suffix-texts")
    buckets = buckets_for(texts, "text")
    gone_path = removed_intervals(texts, length, buckets)
    schema = "doc_id bigint, sha string, n_removed bigint, n_spans bigint, kept_sha256 string" + (", kept binary, spans array<struct<start:bigint,`end`:bigint>>" if with_text else "")
    span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told, known, by_num = _Told(gone_path), None, {}
        for pid, nums, ids, bodies in _texts_by_pid(batches):
            if pid != known:
                known, by_num = pid, {}
                got = [_unpack(p, "<i8", "<i8", "<i8") for p in told.of(pid)]
                if got:
                    d, s, e = (np.concatenate(x) for x in zip(*got, strict=True))
                    o = np.lexsort((s, d))
                    d, s, e = d[o], s[o], e[o]
                    cuts = np.flatnonzero(np.concatenate([[True], d[1:] != d[:-1], [True]]))
                    by_num = {int(d[a]): merged(s[a:b], e[a:b]) for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)}
            out = []
            for i, num, body in zip(ids.tolist(), nums.tolist(), bodies, strict=True):
                s, e = by_num.get(num, (np.empty(0, int), np.empty(0, int)))
                kept = b"".join(body[a:b] for a, b in zip([0, *e.tolist()], [*s.tolist(), len(body)], strict=True))
                row = (i, hashlib.sha256(body).hexdigest(), len(body) - len(kept), len(s), hashlib.sha256(kept).hexdigest())
                out.append((*row, kept, [{"start": a, "end": b} for a, b in zip(s.tolist(), e.tolist(), strict=True)]) if with_text else row)
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), *([pa.binary(), span] if with_text else [])]
            names = ["doc_id", "sha", "n_removed", "n_spans", "kept_sha256", *(["kept", "spans"] if with_text else [])]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names)

    cut_rows = texts.mapInArrow(cut, schema).withColumnRenamed("doc_id", "__id")
    every = rows.select("doc_id", F.sha2("text", 256).alias("__sha"), F.octet_length("text").cast("long").alias("n_bytes"))
    whole = (F.col("n_bytes") >= length) & F.col("doc_id").isNotNull()
    none = F.sha2(F.lit(""), 256)
    joined = every.join(cut_rows, (F.col("doc_id") == F.col("__id")) & (F.col("__sha") == F.col("sha")), "left")
    rep = F.col("__id").isNotNull()
    out = joined.select(
        "doc_id", "n_bytes",
        F.when(rep, F.col("n_removed")).when(whole, F.col("n_bytes")).otherwise(F.lit(0)).cast("long").alias("n_removed"),
        F.when(rep, F.col("n_spans")).when(whole, F.lit(1)).otherwise(F.lit(0)).cast("long").alias("n_spans"),
        F.when(rep, F.col("kept_sha256")).when(whole, none).otherwise(F.col("__sha")).alias("kept_sha256"),
        *(["kept", "spans"] if with_text else []),
    )
    return out
