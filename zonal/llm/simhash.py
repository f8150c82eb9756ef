"""SimHash near-duplicates by the generalised pigeonhole.

Fingerprints: 64 majority bits over the XXH64 values of word shingles. Linking works on
distinct fingerprints. Bits that correlate (on a bounded sample; the sample steers cost, not
results) are grouped into partitions; every fingerprint gets its own thresholds per partition
by dynamic programming over estimated candidate counts, under the sum that the generalised
pigeonhole asks for: with thresholds t_i that sum to tau - m + 1, two fingerprints at most
tau apart agree up to t_i bits in some partition i. Fingerprints are indexed under all their
partition values, probe those within their thresholds, and meet in sorted buckets, where the
exact distance is verified.

Estimates come from a sketch of fixed size, filled over all fingerprints; it steers cost only.
How many partitions there are follows from the number of fingerprints: the most whose values
still tell fingerprints apart. The rows of every bucket are then counted, exactly, and the
fingerprints of buckets that are hot all the same (groups of copies) are linked in another
exact way: each is written under itself and its 64 neighbours at one bit. Two are at most 2
apart exactly if they share such a centre, and a centre has 65 fingerprints around it at
most, all linked to each other; so no group of copies, however large, makes a large bucket
or pairs by its square.

Defined results: null text is empty; a text without words has fingerprint zero and links
like any other; fewer words than a shingle: the sequence is the shingle; rows with equal
ids share the smallest component; a null id is a member but never a component's name unless
all are null; empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, join_by_key, materialize, text_or_empty
from .components import connected_components

SAMPLE = 20_000
#: Bins of the sketch in each partition, a power of two.
BINS = 1 << 16
#: Rows of a bucket that are still compared with each other.
HOT = 64
BITS = 64


def shingle_hashes(words: list[bytes], k: int) -> np.ndarray:
    """XXH64 values of all runs of ``k`` words; fewer words are one run."""
    import xxhash

    h = xxhash.xxh64_intdigest
    joined = b" ".join(words)
    if len(words) <= k:
        return np.array([h(joined, 42)] if words else [], dtype="<u8")
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    return np.array([h(joined[s:e], 42) for s, e in zip(starts[: len(words) - k + 1].tolist(), ends[k - 1 :].tolist(), strict=True)], dtype="<u8")


def fingerprint(text: bytes, k: int = 3) -> int:
    """Fingerprint of one text as an unsigned number."""
    words = text.lower().split()  # on bytes: ASCII letters, ASCII white space
    if not words:
        return 0
    return majority_bits(shingle_hashes(words, k))


def majority_bits(values: np.ndarray) -> int:
    """A bit is 1 if it is set in over half of the values."""
    if len(values) == 1:
        return int(values[0])
    ones = np.zeros(BITS, np.int64)
    for i in range(0, len(values), 1 << 16):
        ones += np.unpackbits(values[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(values), bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, k: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).cast(pa.binary())
            fp = np.array([fingerprint(t.as_py(), k) for t in texts], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp)], ["doc_id", "fp"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, fp bigint")


def hexed(fp) -> F.Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def group_bits(sample: np.ndarray, m: int) -> list[list[int]]:
    """Bits grouped by correlation into ``m`` partitions of nearly equal width."""
    bits = ((sample[:, None] >> np.arange(BITS, dtype=np.uint64)) & np.uint64(1)).astype(np.float64)
    if len(sample) < 2:
        return [list(range(i, BITS, m)) for i in range(m)]
    with np.errstate(invalid="ignore", divide="ignore"):
        corr = np.nan_to_num(np.abs(np.corrcoef(bits.T)))
    np.fill_diagonal(corr, 0)
    left, parts = set(range(BITS)), []
    for i in range(m):
        width = BITS // m + (i < BITS % m)
        seed = max(left, key=lambda b: (corr[b, sorted(left)].sum(), -b))
        part = [seed]
        left.discard(seed)
        while len(part) < width:
            nxt = max(left, key=lambda b: (corr[b, part].mean(), -b))
            part.append(nxt)
            left.discard(nxt)
        parts.append(sorted(part))
    return parts


def part_keys(fp: np.ndarray, parts: list[list[int]]) -> np.ndarray:
    """The bits of each partition side by side, as one number a partition: shape (m, n)."""
    out = np.zeros((len(parts), len(fp)), np.uint64)
    for i, part in enumerate(parts):
        for j, b in enumerate(part):
            out[i] |= ((fp >> np.uint64(b)) & np.uint64(1)) << np.uint64(j)
    return out


def key_bin(keys: np.ndarray, bins: int) -> np.ndarray:
    return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(65 - bins.bit_length())).astype(np.int64)


def allocate(counts: list[np.ndarray], total: int) -> np.ndarray:
    """Thresholds per partition that sum to ``total`` and cost least.

    ``counts[i][:, t + 1]`` is partition i's estimate of candidates at threshold t, from -1 up.
    """
    n, most = counts[0].shape[0], counts[0].shape[1] - 1
    m = len(counts)
    low, width = -m, m * most + 1
    best = np.full((n, width), np.inf)
    best[:, m] = 0  # sum so far 0 is at index m
    picks = []
    for c in counts:
        new, pick = np.full((n, width), np.inf), np.zeros((n, width), np.int8)
        for t in range(-1, most):
            shifted = np.full((n, width), np.inf)
            a, b = max(0, t), width + min(0, t)
            shifted[:, a:b] = best[:, a - t : b - t] + c[:, [t + 1]]
            better = shifted < new
            new[better], pick[better] = shifted[better], t
        best = new
        picks.append(pick)
    out, at = np.zeros((n, m), np.int64), np.full(n, total - low)
    for i in range(m - 1, -1, -1):
        out[:, i] = picks[i][np.arange(n), at]
        at = at - out[:, i]
    return out


def partitions_for(n: int, hot: int = HOT) -> int:
    """The most partitions, up to three, whose values hold few of ``n`` fingerprints each."""
    return next((m for m in (3, 2) if 8 * n <= max(hot, 8) << (BITS // m)), 1)


class Scheme:
    """Partitions and the sketch of candidate counts; small and of fixed size."""

    def __init__(self, parts: list[list[int]], sketch: np.ndarray, tau: int):
        self.parts, self.sketch, self.tau = parts, sketch, tau
        self.mean = sketch.sum(axis=1) / sketch.shape[1]

    def near(self, i: int, keys: np.ndarray, t: int) -> Iterator[np.ndarray]:
        """Keys at exactly ``t`` bits from ``keys`` within partition ``i``."""
        for flip in combinations(range(len(self.parts[i])), t):
            yield keys ^ np.uint64(sum(1 << j for j in flip))

    def estimate(self, i: int, keys: np.ndarray) -> np.ndarray:
        """Fingerprints expected under each key: what its bin has above the mean, and a share of all."""
        above = np.maximum(self.sketch[i][key_bin(keys, self.sketch.shape[1])] - self.mean[i], 0)
        return above + self.sketch[i].sum() / 2.0 ** len(self.parts[i]) + 1

    def rows(self, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(part, key, role, fp): role 1 indexed, 2 probing, 3 both."""
        m, keys = len(self.parts), part_keys(fp, self.parts)
        most = max(1, -(-(self.tau - m + 1) // m)) + 1  # thresholds -1 .. most - 1 are tried
        costs = []
        for i in range(m):
            c = np.zeros((len(fp), most + 1))
            for t in range(most):
                c[:, t + 1] = c[:, t] + sum((self.estimate(i, k) for k in self.near(i, keys[i], t)), np.zeros(len(fp)))
            costs.append(c)
        chosen = allocate(costs, self.tau - m + 1)
        out, every = [], np.arange(len(fp))

        def put(i: int, k: np.ndarray, role: np.ndarray, who: np.ndarray) -> None:
            out.append((np.full(len(k), i, np.int32), k.view(np.int64), role.astype(np.int32), fp[who].view(np.int64)))

        for i in range(m):
            put(i, keys[i], np.where(chosen[:, i] >= 0, 3, 1), every)
            for t in range(1, most):
                who = every[chosen[:, i] >= t]
                for k in self.near(i, keys[i][who], t) if len(who) else ():
                    put(i, k, np.full(len(who), 2), who)
        return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def around(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Rows as of ``Scheme.rows`` that put fingerprints under their centres, as part -1."""
    z = np.concatenate([fp, *(fp ^ np.uint64(1 << b) for b in range(BITS))])
    return np.full(len(z), -1, np.int32), z.view(np.int64), np.full(len(z), 3, np.int32), np.tile(fp, BITS + 1).view(np.int64)


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


def verify(part: np.ndarray, key: np.ndarray, role: np.ndarray, fp: np.ndarray, tau: int) -> tuple[np.ndarray, np.ndarray]:
    """Links among rows sorted by (part, key): verified pairs, probing against indexed."""
    if not len(fp):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    new = np.flatnonzero(np.concatenate([[True], (part[1:] != part[:-1]) | (key[1:] != key[:-1])]))
    size = np.diff(np.concatenate([new, [len(fp)]]))
    u, got = fp.view(np.uint64), []
    for n in np.unique(size[size > 1]).tolist():
        at = new[size == n]
        star = part[at] == -1
        for s in range(1, n):  # all around one centre are links: a star says so
            got.append((fp[at[star]], fp[at[star] + s]))
        at = at[~star]
        for s in range(1, n):
            for e in range(n - s):
                a, b = at + e, at + e + s
                ok = (popcount(u[a] ^ u[b]) <= tau) & (((role[a] & 1) & (role[b] >> 1)) | ((role[b] & 1) & (role[a] >> 1))).astype(bool)
                got.append((fp[a[ok]], fp[b[ok]]))
    if not got:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    a, b = (np.concatenate(x) for x in zip(*got, strict=True))
    keep = a != b
    return a[keep], b[keep]


def near_links(reps: DataFrame, tau: int = 2, parts: int | None = None, hot: int = HOT, bins: int = BINS) -> DataFrame:
    """(a, b): links that join all distinct fingerprints at most ``tau`` bits apart, and no others.

    Where a third fingerprint joins two, their own link may be left out. ``parts`` follows the
    number of fingerprints unless given.
    """
    if tau > 2:
        raise ValueError("hot buckets are exact for up to 2 bits")
    sample = np.array([r[0] for r in reps.select("fp").orderBy(F.xxhash64("fp")).limit(SAMPLE).collect()], dtype=np.int64).view(np.uint64)
    grouped = group_bits(sample, parts or partitions_for(reps.count(), hot))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(grouped), bins), np.int64)
        for b in batches:
            keys = part_keys(b.column(0).to_numpy(zero_copy_only=False).view(np.uint64), grouped)
            for i in range(len(grouped)):
                sums[i] += np.bincount(key_bin(keys[i], bins), minlength=bins)
        at = np.flatnonzero(sums)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(sums.reshape(-1)[at])], ["bin", "n"])

    filled = reps.select("fp").mapInArrow(count, "bin int, n bigint").groupBy("bin").agg(F.sum("n").alias("n")).toArrow()
    sketch = np.zeros(len(grouped) * bins, np.int64)
    sketch[filled.column("bin").to_numpy()] = filled.column("n").to_numpy()
    scheme = reps.sparkSession.sparkContext.broadcast(Scheme(grouped, sketch.reshape(len(grouped), bins), tau))
    kinds = ["part", "key", "role", "fp"]
    ddl = "part int, key bigint, role int, fp bigint"

    def written(make):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                fp = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
                if len(fp):
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in make(fp)], kinds)

        return run

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.empty(0, t) for t in (np.int32, np.int64, np.int32, np.int64)]
        for b in batches:
            held = [np.concatenate([h, b.column(i).to_numpy(zero_copy_only=False)]) for i, h in enumerate(held)]
            if not len(held[0]):
                continue
            last = (held[0] == held[0][-1]) & (held[1] == held[1][-1])
            cut = int(np.argmax(last))  # the last bucket may go on in the next batch
            x, y = verify(*(h[:cut] for h in held), tau)
            held = [h[cut:] for h in held]
            yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], ["a", "b"])
        x, y = verify(*held, tau)
        yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], ["a", "b"])

    rows = materialize(reps.select("fp").mapInArrow(written(lambda fp: scheme.value.rows(fp)), ddl), "simhash-rows")
    crowded = materialize(rows.groupBy("part", "key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > hot), "simhash-hot")
    if not crowded.isEmpty():
        marked = join_by_key(rows, crowded, ["part", "key"], "n", ["fp"], "left")
        stars = marked.where("n is not null").select("fp").distinct().mapInArrow(written(around), ddl)
        rows = marked.where("n is null").select(*kinds).unionByName(stars)
    return rows.repartition("part", "key").sortWithinPartitions("part", "key", "fp").mapInArrow(meet, "a bigint, b bigint")


def near_duplicates(docs: DataFrame, tau: int = 2, k: int = 3, parts: int | None = None, hot: int = HOT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, fp, component_id (smallest doc_id reachable)."""
    fps = materialize(fingerprints(docs, k, id_col, text_col), "simhash")
    reps = materialize(fps.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n")), "simhash-reps")
    roots = materialize(connected_components(near_links(reps, tau, parts, hot)), "simhash-roots")
    by_fp = component_names(reps, "fp", roots)
    discard(reps, roots)
    return join_by_key(fps, by_fp, ["fp"], "n", ["doc_id"]).select("doc_id", "fp", "component_id")


def component_names(nodes: DataFrame, node: str, roots: DataFrame) -> DataFrame:
    """``nodes`` (with a node's smallest id ``least``) and component_id, the smallest id of the component."""
    members = roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
    named = materialize(members.join(nodes.select(F.col(node).alias("node"), "least"), "node"), "names")
    names = materialize(named.groupBy("root").agg(F.min("least").alias("component_id"), F.count(F.lit(1)).alias("n")), "names")
    joined = join_by_key(named.select("node", "root"), names, ["root"], "n", ["node"]).select(F.col("node").alias(node), "component_id")
    out = materialize(nodes.join(joined, node, "left").withColumn("component_id", F.coalesce("component_id", "least")), "component-names")
    discard(named, names)
    return out
