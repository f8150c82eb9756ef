"""Interpolated modified Kneser-Ney n-gram model: counted in Spark, memory-mapped by workers.

Tokens are hashed to 64 bits by NumPy over whole byte buffers. A first pass counts words and
numbers them so that frequent words get small numbers; n-grams are then columns of word
numbers, which compress well. Tasks aggregate the n-grams of some million tokens and send each
bucket one compressed block; a bucket holds all n-grams of its contexts, so one merge gives
counts, the contexts' totals and numbers of once, twice and more often seen words, and the
continuation counts of the next shorter order, which take the same way down to single words.
Contexts so frequent that they would make a bucket large (known from a bounded sample that
steers balance only) are spread over all buckets by word; their partial totals are added up on
the driver, at most some hundred rows a bucket. The number of buckets follows the bytes of
text. A level's exchange is deleted when its result is written.

Buckets are written to the shared folder as sorted arrays: 46 bits of the n-gram's hash, the
first of them as an index, and its count. Scoring tasks map these files into memory and look up sorted blocks of tokens by
binary search. A file's name depends on its content's bucket alone and it is renamed into
place, so tasks can be run again at any time. On storage without a mountable path a worker
fetches a bucket to an unlinked file and maps that.

Every text starts with ``order`` - 1 start marks and ends with an end mark, which is a token.
Unknown words share the uniform floor 1 / (V + 1), so probabilities sum to one.

Defined results: null text is empty: its end mark is its only token; without training rows
the model is the uniform floor; null ids are training rows; repeated rows count each time.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import buckets_for, discard, materialize, shared_path, text_or_empty

U = np.uint64
PIECE, FLUSH_TOKENS, SCORE_TOKENS = 1 << 18, 2_000_000, 800_000
#: Documents looked at for frequent contexts, and the share of n-grams that makes one so.
HOT_SAMPLE, HOT_SHARE = 2000, 0.002
_BYTES = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=U) * U(2) + U(1)
_BASE, _FOLD = U(0x9E3779B97F4A7C15), U(0xD1B54A32D192ED03)


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U(33))
    h = h * U(0xFF51AFD7ED558CCD)
    h = h ^ (h >> U(29))
    h = h * U(0xC4CEB9FE1A85EC53)
    return h ^ (h >> U(32))


def word_hashes(piece: bytes) -> np.ndarray:
    """One hash a word of lower-cased bytes; words end at ASCII white space."""
    x = np.frombuffer(piece, np.uint8)
    if not len(x):
        return np.empty(0, U)
    gap = (x == 32) | ((x >= 9) & (x <= 13))
    start = ~gap
    start[1:] &= gap[:-1]
    starts = np.flatnonzero(start)
    if not len(starts):
        return np.empty(0, U)
    at = np.arange(len(x))
    inside = at - np.maximum.accumulate(np.where(start, at, 0))
    powers = np.full(int(inside.max()) + 1, _BASE)
    powers[0] = 1
    powers = np.multiply.accumulate(powers)
    y = _BYTES[x] * powers[inside]
    y[gap] = 0
    return mix(np.add.reduceat(y, starts))


END_BYTES = b"\xff"  # never part of UTF-8
END = word_hashes(END_BYTES)[0]
#: Numbers of the start mark, of the end mark, and of the first word; unknown words lie far above.
START_ID, END_ID, FIRST_ID, UNKNOWN = U(0), U(1), 2, U(1 << 63)


def token_blocks(texts: list[bytes]) -> Iterator[np.ndarray]:
    """The tokens of all texts in turn, each text ended by END, in pieces of bounded size."""
    held, size = [], 0
    for text in texts:
        text = text.lower()
        at = 0
        while len(text) - at > PIECE:  # a long text is cut behind white space
            cut = min((i for i in (text.find(w, at + PIECE) for w in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c")) if i >= 0), default=-1)
            if cut < 0:
                break
            held.append(text[at : cut + 1])
            yield word_hashes(b" ".join(held))
            held, size, at = [], 0, cut + 1
        held += [text[at:], END_BYTES]
        size += len(text) - at
        if size > PIECE:
            yield word_hashes(b" ".join(held))
            held, size = [], 0
    if held:
        yield word_hashes(b" ".join(held))


def windows(tokens: np.ndarray, tail: np.ndarray, order: int) -> np.ndarray:
    """(order, n): the word number in the last row, those before it above, START_ID before a text."""
    every = np.concatenate([tail, tokens])
    n, rows = len(tokens), [tokens]
    fresh = np.zeros(n, bool)
    for k in range(1, order):
        before = every[len(tail) - k : len(tail) - k + n]
        fresh = fresh | (before == END_ID)
        rows.append(np.where(fresh, START_ID, before))
    return np.stack(rows[::-1])


def key_of(words: np.ndarray) -> np.ndarray:
    """One hash for each column of ``words`` (k, n)."""
    h = mix(words[0] + U(len(words)))
    for w in words[1:]:
        h = mix(h * _FOLD + w)
    return h


def home_bucket(words: np.ndarray, buckets: int, hot: np.ndarray) -> np.ndarray:
    """Bucket of n-grams: by context, or by word where the context is hot or empty."""
    key = key_of(words[:-1] if len(words) > 1 else words)
    if len(words) > 1 and len(hot):
        key = np.where(np.isin(key, hot), key_of(words[-1:]), key)
    return ((key >> U(20)) % U(buckets)).astype(np.int32)


def sort_keys(words: np.ndarray) -> list[np.ndarray]:
    """As few numbers as hold the columns of ``words``, most significant first."""
    bits = max(int(words.max()).bit_length(), 1) if words.size else 1
    keys, per = [], max(64 // bits, 1)
    for i in range(0, len(words), per):
        key = words[i]
        for w in words[i + 1 : i + per]:
            key = (key << U(bits)) | w
        keys.append(key)
    return keys


def squash(words: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Equal n-grams merged, in order of their word numbers."""
    if not words.shape[1]:
        return words, count
    keys = sort_keys(words)
    order = np.argsort(keys[0]) if len(keys) == 1 else np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    new[0] = True
    for key in keys:
        key = key[order]
        new[1:] |= key[1:] != key[:-1]
    first = np.flatnonzero(new)
    return words[:, order[first]], np.add.reduceat(count[order], first)


_BLOCK = ["bucket", "n", "payload"]
_BLOCK_DDL = "bucket int, n bigint, payload binary"


def planes(x: np.ndarray) -> bytes:
    """Whole numbers byte by byte, lowest bytes first, without the planes that are all zero."""
    raw = np.ascontiguousarray(x, "<u8").view(np.uint8).reshape(-1, 8).T
    used = int(x.max()).bit_length() + 7 >> 3 if len(x) else 0
    return bytes([used]) + raw[:used].tobytes()


def from_planes(raw: bytes, at: int, n: int) -> tuple[np.ndarray, int]:
    used, out = raw[at], np.zeros((n, 8), np.uint8)
    out[:, :used] = np.frombuffer(raw, np.uint8, used * n, at + 1).reshape(used, n).T
    return out.reshape(-1).view("<u8"), at + 1 + used * n


def blocks(words: np.ndarray, count: np.ndarray, home: np.ndarray, buckets: int) -> pa.RecordBatch:
    """One row a bucket: the columns of its n-grams, compressed; ``words`` are in order."""
    order = np.argsort(home, kind="stable")
    ends = np.searchsorted(home[order], np.arange(buckets + 1))
    rows, codec = [], pa.Codec("zstd", 1)
    for b in np.flatnonzero(np.diff(ends)).tolist():
        pick = order[ends[b] : ends[b + 1]]
        step = np.diff(words[0][pick], prepend=U(0))  # never falls
        body = b"".join([planes(step), *(planes(w[pick]) for w in words[1:]), planes(count[pick])])
        rows.append((b, len(pick), len(body).to_bytes(8, "little") + codec.compress(body, asbytes=True)))
    cols = list(zip(*rows, strict=True)) or [[], [], []]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.int64(), pa.binary()), strict=True)], _BLOCK)


def unblock(n: int, payload: bytes, k: int) -> tuple[np.ndarray, np.ndarray]:
    raw = pa.Codec("zstd").decompress(payload[8:], int.from_bytes(payload[:8], "little"), asbytes=True)
    cols, at = [], 0
    for _ in range(k + 1):
        col, at = from_planes(raw, at, n)
        cols.append(col)
    cols[0] = np.cumsum(cols[0], dtype=U)
    return np.stack(cols[:k]), cols[k].astype(np.int64)


# ---- files in the shared folder -------------------------------------------------------------


def _fs(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def put_arrays(uri: str, arrays: dict[str, np.ndarray]) -> None:
    """Write arrays one after the other, 64-byte aligned, behind an index; then rename."""
    import os
    import uuid

    fs, path = _fs(uri)
    index, at, body = {}, 0, []
    for name, a in arrays.items():
        a = np.ascontiguousarray(a)
        index[name] = (a.dtype.str, len(a), at)
        pad = -a.nbytes % 64
        body += [a.tobytes(), b"\0" * pad]
        at += a.nbytes + pad
    head = repr(index).encode()
    head += b" " * (-(len(head) + 8) % 64)
    temp = f"{path}.{uuid.uuid4().hex[:8]}.{os.getpid()}"
    with fs.open_output_stream(temp) as out:
        out.write(len(head).to_bytes(8, "little") + head)
        for b in body:
            out.write(b)
    try:
        fs.move(temp, path)
    except OSError:  # some storage doesn't replace: an earlier run of this task has left the same file
        if not fs.get_file_info(path).is_file:
            raise
        fs.delete_file(temp)


def map_arrays(uri: str) -> dict[str, np.ndarray]:
    """The arrays of a file, mapped into memory."""
    import ast

    fs, path = _fs(uri)
    if fs.type_name != "local":
        local = tempfile.TemporaryFile()  # has no name: gone when unmapped, whatever happens
        with fs.open_input_stream(path) as source:
            while chunk := source.read(1 << 24):
                local.write(chunk)
        local.flush()
        data = np.memmap(local, np.uint8, "r")
    else:
        data = np.memmap(path, np.uint8, "r")
    data = data.view(np.ndarray)  # still mapped; slices of the subclass are slow
    n = int.from_bytes(data[:8].tobytes(), "little")
    index = ast.literal_eval(data[8 : 8 + n].tobytes().decode())
    out = {}
    for name, (kind, size, at) in index.items():
        begin = 8 + n + at
        out[name] = data[begin : begin + size * np.dtype(kind).itemsize].view(kind)
    return out


# ---- sorted arrays --------------------------------------------------------------------------


#: Bits of an n-gram's hash that are kept within its bucket, and those of them that index.
KEY_BITS, TOP_BITS = 46, 14


def short_key(words: np.ndarray) -> np.ndarray:
    return key_of(words) >> U(64 - KEY_BITS)


def by_bucket(bucket: np.ndarray, key: np.ndarray, buckets: int) -> Iterator[tuple[int, np.ndarray]]:
    """(bucket, places in order of the short key) of every bucket met."""
    order = np.argsort((bucket.astype(U) << U(48)) | key) if buckets <= 1 << 16 else np.lexsort((key, bucket))
    at = bucket[order]
    cuts = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1], [True]])) if len(at) else [0]
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        yield int(at[a]), order[a:b]


def indexed(key: np.ndarray) -> dict[str, np.ndarray]:
    """Sorted short keys: where each value of the top bits begins, and the low bits."""
    top = np.searchsorted(key >> U(KEY_BITS - TOP_BITS), np.arange((1 << TOP_BITS) + 1, dtype=U))
    return {"top": top.astype(np.uint32), "low": key.astype(np.uint32)}


def locate(f: dict[str, np.ndarray], key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(which keys are there, their places)."""
    low, top = f["low"], (key >> U(KEY_BITS - TOP_BITS)).astype(np.int64)
    if not len(low):
        return np.zeros(len(key), bool), np.empty(0, np.int64)
    a, end = f["top"][top].astype(np.int64), f["top"][top + 1].astype(np.int64)
    b, want = end, key.astype(np.uint32)
    for _ in range(int((b - a).max()).bit_length()):
        mid = (a + b) >> 1
        less = (a < b) & (low[np.minimum(mid, len(low) - 1)] < want)
        a, b = np.where(less, mid + 1, a), np.where(less, b, np.minimum(mid, b))
    place = np.minimum(a, len(low) - 1)
    ok = (a < end) & (low[place] == want)
    return ok, place[ok]


def slim(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint32 if not len(x) or int(x.max()) < 1 << 32 else U)


def narrow(x: np.ndarray, name: str) -> dict[str, np.ndarray]:
    """Numbers as single bytes; where they don't fit, place and number beside."""
    many = np.flatnonzero(x >= 255)
    return {name: np.minimum(x, 255).astype(np.uint8), f"{name}_at": many.astype(np.uint32), f"{name}_is": slim(x[many])}


def widened(f: dict[str, np.ndarray], name: str, place: np.ndarray) -> np.ndarray:
    got = f[name][place].astype(np.float64)
    big = got == 255
    if big.any():
        got[big] = f[f"{name}_is"][np.searchsorted(f[f"{name}_at"], place[big])]
    return got


class Files:
    """The files of a model in this process, mapped when first needed."""

    def __init__(self, path: str, buckets: int):
        from pyarrow.fs import FileSelector

        self.path, self.buckets, self.open = path, buckets, {}
        fs, where = _fs(path)
        self.there = {f.base_name for f in fs.get_file_info(FileSelector(where))}

    def get(self, kind: str, level: int, bucket: int) -> dict[str, np.ndarray] | None:
        name = _name("", kind, level, bucket)[1:]
        if name not in self.there:
            return None
        if name not in self.open:
            self.open[name] = map_arrays(f"{self.path}/{name}")
        return self.open[name]

    def numbers(self, tokens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(word numbers, counts in the training texts) of hashed tokens."""
        kinds, which = np.unique(tokens, return_inverse=True)
        ids, times = (kinds >> U(1)) | UNKNOWN, np.zeros(len(kinds))
        for b, who in by_bucket(((kinds >> U(20)) % U(self.buckets)).astype(np.int32), kinds >> U(16), self.buckets):
            f = self.get("v", 0, b)
            if f is not None:
                at = np.minimum(np.searchsorted(f["hash"], kinds[who]), len(f["hash"]) - 1)
                ok = f["hash"][at] == kinds[who]
                ids[who[ok]], times[who[ok]] = f["id"][at[ok]], f["times"][at[ok]]
        ids[kinds == END] = END_ID
        return ids[which], times[which]


_FILES: dict[str, Files] = {}  # for counting, when only the vocabulary is there


def _files(path: str, buckets: int) -> Files:
    if path not in _FILES:
        _FILES.clear()
        _FILES[path] = Files(path, buckets)
    return _FILES[path]


# ---- counting -------------------------------------------------------------------------------


@dataclass
class Model:
    """What scoring needs beside the mapped files."""

    path: str
    order: int
    buckets: int
    hot: list[np.ndarray]
    hot_stats: list[dict[int, tuple[int, ...]]] = field(default_factory=list)
    discounts: list[np.ndarray] = field(default_factory=list)
    tokens: int = 0
    types: int = 0
    continuations: int = 0
    floor_mass: float = 1.0


def discounts_of(n: np.ndarray) -> np.ndarray:
    """Discounts for counts 0, 1, 2 and 3 or more, from the numbers of counts 1 to 4."""
    n1, n2, n3, n4 = (float(x) for x in n)
    y = n1 / (n1 + 2 * n2) if n1 and n2 else 0.5
    d1 = 1 - 2 * y * n2 / n1 if n1 and n2 else 0.5
    d2 = 2 - 3 * y * n3 / n2 if n2 and n3 else 1.0
    d3 = 3 - 4 * y * n4 / n3 if n3 and n4 else 1.5
    return np.array([0.0, min(max(d1, 0.05), 1.0), min(max(d2, 0.05), 2.0), min(max(d3, 0.05), 3.0)])


def _name(path: str, kind: str, level: int, bucket: int) -> str:
    return f"{path}/{kind}{level}-{bucket:06d}"


def _merged(done, k: int):
    """A task over blocks sorted by bucket: ``done(bucket, columns, counts)`` for each bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, parts = None, []

        def settle() -> Iterator[pa.RecordBatch]:
            if parts:
                words, count = np.concatenate([p[0] for p in parts], axis=1), np.concatenate([p[1] for p in parts])
                parts.clear()
                out = done(now, *squash(words, count))
                if out is not None:
                    yield out

        for batch in batches:
            for i in range(batch.num_rows):
                bucket = batch.column(0)[i].as_py()
                if bucket != now:
                    yield from settle()
                now = bucket
                parts.append(unblock(batch.column(1)[i].as_py(), batch.column(2)[i].as_py(), k))
        yield from settle()

    return run


def _flushed(emit, start):
    """A task over texts: tokens are gathered by ``start()`` objects and sent every so many."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take, held, n = start(), [], 0
        for batch in batches:
            for tokens in token_blocks(batch.column(0).cast(pa.binary()).to_pylist()):
                held.append(take(tokens))
                n += len(tokens)
                if n >= FLUSH_TOKENS:
                    yield emit(held)
                    held, n = [], 0
        if held:
            yield emit(held)

    return run


def _vocabulary(path: str, buckets: int):
    """(task that counts words, task that numbers a bucket's words)."""

    def emit(held: list[np.ndarray]) -> pa.RecordBatch:
        kinds, times = np.unique(np.concatenate(held), return_counts=True)
        return blocks(kinds[None], times, ((kinds >> U(20)) % U(buckets)).astype(np.int32), buckets)

    def done(bucket: int, words: np.ndarray, count: np.ndarray) -> None:
        rank = np.empty(len(count), U)
        rank[np.argsort(-count, kind="stable")] = np.arange(len(count), dtype=U)
        put_arrays(_name(path, "v", 0, bucket), {"hash": words[0], "id": slim(U(FIRST_ID) + rank * U(buckets) + U(bucket)), "times": slim(count)})
        put_arrays(_name(path, "s", 0, bucket), {"stats": np.array([len(count), int(count.sum())], np.int64)})

    return _flushed(emit, lambda: lambda tokens: tokens), _merged(done, 1)


def _grams(path: str, order: int, buckets: int):
    """Objects that turn tokens into n-grams of word numbers."""

    def start():
        files, tail = _files(path, buckets), np.full(order - 1, END_ID)

        def take(tokens: np.ndarray) -> np.ndarray:
            nonlocal tail
            ids = files.numbers(tokens)[0]
            rows = windows(ids, tail, order)
            tail = np.concatenate([tail, ids])[-(order - 1) :]
            return rows

        return take

    return start


def _merge(level: int, path: str, buckets: int, hot: list[np.ndarray]):
    """The task that merges a bucket's n-grams of ``level`` words and sends on shorter ones."""

    def done(bucket: int, words: np.ndarray, count: np.ndarray) -> pa.RecordBatch | None:
        stats = np.array([*(int((count == i).sum()) for i in (1, 2, 3, 4)), len(count), int(count.sum())], np.int64)
        key = short_key(words)
        order_ = np.argsort(key)
        put_arrays(_name(path, "n", level, bucket), indexed(key[order_]) | narrow(count[order_], "count"))
        if level == 1:
            put_arrays(_name(path, "s", 1, bucket), {"stats": stats, "hot": np.empty(0, np.int64)})
            return None
        new = np.zeros(words.shape[1], bool)
        new[0] = True
        for w in words[:-1]:
            new[1:] |= w[1:] != w[:-1]
        first = np.flatnonzero(new)
        sums = [np.add.reduceat(x.astype(np.int64), first) for x in (count, count == 1, count == 2, count >= 3)]  # total, n1, n2, n3
        context = key_of(words[:-1, first])
        is_hot = np.isin(context, hot[level])
        spread = np.stack([context[is_hot].view(np.int64), *(s[is_hot] for s in sums)]) if is_hot.any() else np.empty((5, 0), np.int64)
        put_arrays(_name(path, "s", level, bucket), {"stats": stats, "hot": spread.reshape(-1)})
        context = context[~is_hot] >> U(64 - KEY_BITS)
        order_ = np.argsort(context)
        total, n1, n2, n3 = (x[~is_hot][order_] for x in sums)
        rich = np.flatnonzero(n3)  # elsewhere the total is n1 + 2 n2
        more = {"rich": rich.astype(np.uint32), "n3": slim(n3[rich]), "total": slim(total[rich])}
        put_arrays(_name(path, "c", level, bucket), indexed(context[order_]) | narrow(n1, "n1") | narrow(n2, "n2") | more)
        shorter, sent = squash(words[1:], np.ones(len(count), np.int64))
        return blocks(shorter, sent, home_bucket(shorter, buckets, hot[level - 1]), buckets)

    return _merged(done, level)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 10 == 0, F.lit(False))


def _hot_contexts(texts: DataFrame, order: int, path: str, buckets: int) -> list[np.ndarray]:
    """For every level the contexts that hold a large share of the n-grams of some documents.

    Executors count; the driver gets the frequent ones only, at most 1 / HOT_SHARE a level.
    """
    start = _grams(path, order, buckets)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take = start()
        for batch in batches:
            for tokens in token_blocks(batch.column(0).cast(pa.binary()).to_pylist()):
                rows = take(tokens)
                for level in range(2, order + 1):
                    keys, n = np.unique(key_of(rows[order - level : order - 1]), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), level, np.int32)), pa.array(keys.view(np.int64)), pa.array(n)], ["level", "key", "n"])
                yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([0]), pa.array([len(tokens)])], ["level", "key", "n"])

    seen = texts.limit(HOT_SAMPLE).mapInArrow(count, "level int, key bigint, n bigint").groupBy("level", "key").agg(F.sum("n").alias("n"))
    seen = materialize(seen, "ngrams-sample")
    total = seen.where("level = 0").agg(F.sum("n")).first()[0] or 0
    often = seen.where((F.col("level") > 0) & (F.col("n") >= max(HOT_SHARE, 0.5 / buckets) * total)).collect()
    discard(seen)
    return [np.sort(np.array([r["key"] for r in often if r["level"] == level], np.int64).view(U)) for level in range(order + 1)]


#: Makes Spark delete the exchanges of a finished job; a running session may set it.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def train(docs: DataFrame, order: int = 3, text_col: str = "text", buckets: int | None = None) -> Model:
    """Count the n-grams of all rows and write the model's files."""
    if order < 2:
        raise ValueError("order must be 2 or more")
    spark = docs.sparkSession
    texts = docs.select(text_or_empty(text_col).alias("text"))
    buckets = buckets or buckets_for(texts, "text", 2)  # an n-gram's columns take more than its text
    path = shared_path(spark, "ngrams")
    fs, where = _fs(path)
    fs.create_dir(where, recursive=True)
    dealt = lambda rows: rows.repartition(buckets, "bucket").sortWithinPartitions("bucket")
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        count, number = _vocabulary(path, buckets)
        dealt(texts.mapInArrow(count, _BLOCK_DDL)).mapInArrow(number, _BLOCK_DDL).count()
        hot = _hot_contexts(texts, order, path, buckets)

        def emit(held: list[np.ndarray]) -> pa.RecordBatch:
            words = np.concatenate(held, axis=1)
            words, times = squash(words, np.ones(words.shape[1], np.int64))
            return blocks(words, times, home_bucket(words, buckets, hot[order]), buckets)

        rows = texts.mapInArrow(_flushed(emit, _grams(path, order, buckets)), _BLOCK_DDL)
        for level in range(order, 1, -1):
            shorter = materialize(dealt(rows).mapInArrow(_merge(level, path, buckets, hot), _BLOCK_DDL), f"ngrams-{level}")
            discard(rows)
            rows = shorter
        dealt(rows).mapInArrow(_merge(1, path, buckets, hot), _BLOCK_DDL).count()
        discard(rows)
    finally:
        spark.conf.set(CLEANUP, before) if before is not None else spark.conf.unset(CLEANUP)
    model = Model(path, order, buckets, hot)
    for level in range(order + 1):
        sums, hot_stats = np.zeros(6 if level else 2, np.int64), {}
        for b in range(buckets):
            if fs.get_file_info(_name(where, "s", level, b)).is_file:
                got = map_arrays(_name(path, "s", level, b))
                sums += got["stats"]
                for key, *part in got["hot"].reshape(5, -1).T.tolist() if level else ():
                    hot_stats[key] = tuple(a + p for a, p in zip(hot_stats.get(key, (0,) * 4), part, strict=True))
        model.discounts.append(discounts_of(sums[:4]) if level else np.zeros(4))
        model.hot_stats.append(hot_stats)
        if level == 0:
            model.types, model.tokens = (int(x) for x in sums)
        if level == 1:
            model.continuations = int(sums[5])
            d, n = model.discounts[1], sums[:4]
            over = model.types - int(n[0]) - int(n[1])
            model.floor_mass = float((d[1] * n[0] + d[2] * n[1] + d[3] * over) / model.continuations) if model.continuations else 1.0
    return model


# ---- scoring --------------------------------------------------------------------------------


class Mapped:
    """A model in this process."""

    def __init__(self, model: Model):
        self.m, self.files = model, Files(model.path, model.buckets)  # lists all files of the finished model
        self.hot = []
        for stats in model.hot_stats:
            keys = np.array(sorted(stats), np.int64)
            table = np.array([stats[k] for k in keys.tolist()], np.float64).reshape(-1, 4).T
            order = np.argsort(keys.view(U))
            self.hot.append((keys.view(U)[order], table[:, order]))

    def counts(self, words: np.ndarray) -> np.ndarray:
        """Counts of n-grams; for shorter than the longest, continuation counts."""
        level, key = len(words), short_key(words)
        count = np.zeros(words.shape[1])
        for b, who in by_bucket(home_bucket(words, self.m.buckets, self.m.hot[level]), key, self.m.buckets):
            f = self.files.get("n", level, b)
            if f is not None:
                ok, place = locate(f, key[who])
                count[who[ok]] = widened(f, "count", place)
        return count

    def contexts(self, words: np.ndarray, level: int) -> np.ndarray:
        """(4, n): totals and numbers of words seen once, twice and more behind contexts."""
        key, out = key_of(words), np.zeros((4, words.shape[1]))
        hot_keys, hot_table = self.hot[level]
        cold = np.arange(len(key))
        if len(hot_keys):
            is_hot = np.isin(key, hot_keys)
            out[:, is_hot] = hot_table[:, np.searchsorted(hot_keys, key[is_hot])]
            cold = np.flatnonzero(~is_hot)
            key = key[cold]
        for b, who in by_bucket(((key >> U(20)) % U(self.m.buckets)).astype(np.int32), key >> U(64 - KEY_BITS), self.m.buckets):
            f = self.files.get("c", level, b)
            if f is None:
                continue
            ok, place = locate(f, key[who] >> U(64 - KEY_BITS))
            to = cold[who[ok]]
            n1, n2 = widened(f, "n1", place), widened(f, "n2", place)
            out[0, to], out[1, to], out[2, to] = n1 + 2 * n2, n1, n2
            if len(f["rich"]):
                at = np.minimum(np.searchsorted(f["rich"], place), len(f["rich"]) - 1)
                rich = f["rich"][at] == place
                out[0, to[rich]], out[3, to[rich]] = f["total"][at[rich]], f["n3"][at[rich]]
        return out

    def probabilities(self, rows: np.ndarray) -> np.ndarray:
        """Probability of each window's last word."""
        m = self.m
        less = lambda level, c: np.maximum(c - m.discounts[level][np.minimum(c, 3).astype(np.int64)], 0)
        p = np.full(rows.shape[1], m.floor_mass / (m.types + 1))
        if m.continuations:
            p += less(1, self.counts(rows[-1:])) / m.continuations
        for level in range(2, m.order + 1):
            total, n1, n2, n3 = self.contexts(rows[-level:-1], level)
            seen = total > 0
            if not seen.any():
                continue
            d = m.discounts[level]
            rest = (d[1] * n1 + d[2] * n2 + d[3] * n3)[seen]
            p[seen] = (less(level, self.counts(rows[-level:][:, seen])) + rest * p[seen]) / total[seen]
        return p


_MAPPED: dict[str, Mapped] = {}


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score, perplexity."""
    kinds = {"doc_id": pa.int64(), "n_tokens": pa.int64(), "n_known": pa.int64(), "train_tokens": pa.int64(), "base_score": pa.float64(), "score": pa.float64(), "perplexity": pa.float64()}
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        if m.path not in _MAPPED:
            _MAPPED.clear()
            _MAPPED[m.path] = Mapped(m)
        mapped = _MAPPED[m.path]
        for batch in batches:
            sums = np.zeros((4, batch.num_rows))
            tail, doc, held = np.full(m.order - 1, END_ID), 0, []

            def settle() -> None:
                nonlocal held, doc
                rows, raw = np.concatenate([h[0] for h in held], axis=1), np.concatenate([h[1] for h in held])
                held = []
                p = mapped.probabilities(rows)
                ended = rows[-1] == END_ID
                owner = doc + np.concatenate([[0], np.cumsum(ended)[:-1]])
                doc += int(ended.sum())
                base = np.log10((raw + 0.1) / (m.tokens + 0.1 * (m.types + 1)))
                for i, x in enumerate((None, raw > 0, base, np.log10(p))):
                    sums[i] += np.bincount(owner, x, minlength=batch.num_rows)

            for tokens in token_blocks(batch.column(1).cast(pa.binary()).to_pylist()):
                ids, raw = mapped.files.numbers(tokens)
                held.append((windows(ids, tail, m.order), raw))
                tail = np.concatenate([tail, ids])[-(m.order - 1) :]
                if sum(len(h[1]) for h in held) >= SCORE_TOKENS:
                    settle()
            if held:
                settle()
            n, known, base, model_score = sums
            perplexity = 10 ** np.minimum(-model_score / np.maximum(n, 1), 300)
            cols = [batch.column(0), n.astype(np.int64), known.astype(np.int64), np.full(batch.num_rows, m.tokens, np.int64), base, model_score, perplexity]
            yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in cols], list(kinds))

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double, perplexity double")
