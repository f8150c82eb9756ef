"""The SimHash operator's general mode: near-duplicates by similarity, each link verified.

Two documents are linked if the Jaccard similarity of their sets of ``k``-word shingles is
``percent`` or more. Documents with equal sets are one node. Three steps:

1. Fingerprints of the sets are linked by the generalised pigeonhole (``simhash.near_links``):
   candidates within two bits.
2. Most pairs at 0.8 lie further apart than any number of bits that can be probed (2 to 11 of
   64 were seen). Their candidates are nodes that agree in a band of minimum hashes: with 24
   bands of 4 a pair at 0.8 is overlooked with a probability of 3e-6, one at 0.9 with 1e-11.
3. Candidates are decided on their whole shingle sets, so no link is wrong but for collisions
   of 64-bit hashes.

A bucket holds few nodes or a group of copies. Its nodes are first held against one of them,
another in each bucket, or the one that looks like the original; what that links is one
component. Where many pairs of different
components are left, further rounds follow with other leaders, so a group of copies costs
about its size times the rounds, not its square. Only then are nodes of different components
compared: directly in small buckets; in others, as pages of one template give, if they share
one of their rarest shingles: of sets that are 0.8 alike, the larger one's rarest fifth and one
more and the smaller one's rarest ninth and one more always share one. All of this saves work only, no pair is given up. Joins cut hot buckets and
leaders into pieces. What stays quadratic is a group of texts that are nearly, but not quite,
alike and linked to nothing.

Defined results: null text is empty; texts without words are equal to each other; fewer words
than a shingle: the sequence is the shingle; a null id is a member but never a component's
name unless all are null; empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, join_by_key, materialize, text_or_empty
from .components import connected_components
from .simhash import component_names, majority_bits, near_links, shingle_hashes

BANDS, ROWS = 24, 4
#: Nodes of several components in a bucket that are still compared with each other.
CROWD = 8
#: Rounds of leaders at most, and the pairs a row of a bucket that aren't worth another one.
ROUNDS, FEW = 2, 1
_RNG = np.random.default_rng(20)
_XOR = _RNG.integers(0, 1 << 32, BANDS * ROWS, np.uint32)[:, None]
_MUL = _RNG.integers(0, 1 << 32, BANDS * ROWS, np.uint32)[:, None] | np.uint32(1)


def shingle_set(text: bytes, k: int) -> np.ndarray:
    return np.unique(shingle_hashes(text.lower().split(), k))


def node_of(grams: np.ndarray) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(grams.tobytes(), 7)


def bands_of(grams: np.ndarray) -> np.ndarray:
    """One key a band, of its place and its minimum hashes."""
    low = np.full(BANDS * ROWS, 0xFFFFFFFF, np.uint32)
    h = (grams >> np.uint64(32)).astype(np.uint32)
    for i in range(0, len(h), 1 << 13):
        np.minimum(low, ((h[i : i + (1 << 13)] ^ _XOR) * _MUL).min(axis=1), out=low)
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for part in low.reshape(BANDS, ROWS).T:
        key = (key ^ part) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return key


def _shingled(docs: DataFrame, k: int, id_col: str, text_col: str, whole: bool) -> DataFrame:
    """doc_id, node, size and either fp and the bands or the whole set of every row."""
    names = ["doc_id", "node", "size", *(["grams"] if whole else ["fp", "bands"])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = [shingle_set(t.as_py(), k) for t in b.column(1).cast(pa.binary())]
            node = np.array([node_of(g) for g in sets], np.uint64).view(np.int64)
            size = np.array([len(g) for g in sets], np.int32)
            lists = [(g if whole else bands_of(g)).view(np.int64) for g in sets]
            ends = np.cumsum([0, *map(len, lists)]).astype(np.int32)
            flat = np.concatenate([np.empty(0, np.int64), *lists])
            cols = [b.column(0), pa.array(node), pa.array(size)]
            if not whole:
                cols.append(pa.array(np.array([majority_bits(g) if len(g) else 0 for g in sets], np.uint64).view(np.int64)))
            yield pa.RecordBatch.from_arrays([*cols, pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, node bigint, size int, " + ("grams array<bigint>" if whole else "fp bigint, bands array<bigint>"))


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets are similar enough."""
    often = pairs.groupBy("a").agg(F.count(F.lit(1)).alias("n"))
    first = materialize(often.join(sets.select(F.col("node").alias("a"), F.col("grams").alias("ga")), "a"), "similar-first")
    seconds = pairs.join(sets.select(F.col("node").alias("b"), F.col("grams").alias("gb")), "b")
    met = join_by_key(seconds, first, ["a"], "n", ["b"])
    met = met.select("a", "b", F.size(F.array_intersect("ga", "gb")).alias("both"), (F.size("ga") + F.size("gb")).alias("sum"))
    return met.where(F.col("both") * 100 >= (F.col("sum") - F.col("both")) * percent).select("a", "b")


def _near(x: str, y: str, percent: int):
    """Sizes that allow the similarity."""
    return F.least(F.col(x), F.col(y)) * 100 >= F.greatest(F.col(x), F.col(y)) * percent


def _stars(rows: DataFrame, percent: int, seed: int = 0) -> DataFrame:
    """Every node beside one of each bucket: a, b. It is first the one of the greatest weight,
    in later rounds, and without weights, one drawn by hash.

    Rows that have their component in ``root`` are left out where it is the leader's.
    """
    heavy = [(-F.col("weight")).alias("w")] if "weight" in rows.columns and not seed else []
    lead = F.struct(*heavy, F.xxhash64("key", "node", F.lit(seed)).alias("h"), "node", "size", *(["root"] if "root" in rows.columns else []))
    leaders = rows.groupBy("key").agg(F.min(lead).alias("s"), F.count(F.lit(1)).alias("n")).where("n > 1")
    names = [F.col("s.node").alias("a"), F.col("s.size").alias("a_size"), *([F.col("s.root").alias("a_root")] if "root" in rows.columns else [])]
    leaders = materialize(leaders.select("key", *names, "n"), "similar-leaders")
    met = join_by_key(rows.drop("n"), leaders, ["key"], "n", ["node"]).where((F.col("node") != F.col("a")) & _near("size", "a_size", percent))
    if "root" in rows.columns:
        met = met.where("root <> a_root")
    return met.select(F.least("a", "node").alias("a"), F.greatest("a", "node").alias("b")).distinct()


def _split(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """Rows of buckets that hold several components, with root, and n, their bucket's rows."""
    placed = rows.join(roots, "node", "left").select("key", "node", "size", "indexed", "shared", F.coalesce("root", "node").alias("root"))
    placed = materialize(placed, "similar-placed")
    split = placed.groupBy("key").agg(F.min("root").alias("r"), F.max("root").alias("s"), F.count(F.lit(1)).alias("n"), F.bool_or("indexed").alias("any"))
    split = materialize(split.where("r < s and any").select("key", "n"), "similar-buckets")
    out = materialize(join_by_key(placed, split, ["key"], "n", ["node"]), "similar-split")
    discard(placed, split)
    return out


def _open_pairs(split: DataFrame) -> tuple[int, int]:
    """(pairs of indexed and other rows of different components in one bucket, rows)."""
    per = split.groupBy("key", "root").agg(F.count(F.lit(1)).alias("c"), F.count_if("indexed").alias("i"), F.max("n").alias("n"))
    got = per.agg(F.sum(F.col("i") * (F.col("n") - F.col("c"))), F.sum("c")).first()
    return got[0] or 0, got[1] or 0


def _across(split: DataFrame, percent: int) -> DataFrame:
    """Pairs a, b of different components that share a bucket, the smaller one indexed there, and
    that have enough shingles which occur elsewhere at all."""
    other = split.select("key", F.col("node").alias("b"), F.col("size").alias("b_size"), F.col("shared").alias("b_shared"), F.col("root").alias("b_root"))
    enough = F.least("shared", "b_shared") * (100 + percent) >= (F.col("size") + F.col("b_size")) * percent
    ordered = F.struct("size", "node") < F.struct("b_size", "b")
    met = split.where("indexed").drop("n").join(other, "key").where(ordered & (F.col("root") != F.col("b_root")) & _near("size", "b_size", percent) & enough)
    return met.select(F.least("node", "b").alias("a"), F.greatest("node", "b").alias("b")).distinct()


def _settled(rows: DataFrame, found: DataFrame, sets: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """(links, rows of buckets that still hold several components) after rounds of leaders.

    A bucket's nodes meet another leader each round, those of the leader's component left out,
    until few pairs of different components are left or rounds no longer help. This only saves
    work: what is left is compared by the caller.
    """
    split = _split(rows, connected_components(found))
    left, n = _open_pairs(split)
    for seed in range(1, ROUNDS + 1):
        if left <= FEW * n:
            break
        more = materialize(_verified(_stars(split, percent, seed), sets, percent), "similar-links")
        found = materialize(found.union(more), "similar-links")
        before, split = split, _split(split.select("key", "node", "size", "indexed", "shared"), connected_components(found))
        discard(before, more)
        left, n = _open_pairs(split)
    return found, split


def _rarest(sets: DataFrame, percent: int) -> DataFrame:
    """(key, node, size, indexed, shared, weight): each set's rarest shingles, as many as similar
    sets share one of; how many of a set's shingles others have, and how common they are: of a
    group of copies the original has the greatest weight.

    A set and a smaller one that is similar share a shingle that is among the rarest
    size - percent of size + 1 of the larger, and, as they must agree in twice as much of the
    smaller one's size over 100 + percent, among still fewer of the smaller: those are indexed.
    """
    grams = sets.select("node", F.size("grams").alias("size"), F.explode("grams").alias("key"))
    seen = materialize(grams.groupBy("key").agg(F.count(F.lit(1)).alias("n")), "similar-seen")
    ranked = join_by_key(grams, seen, ["key"], "n", ["node"])
    order = Window.partitionBy("node").orderBy("n", "key")
    need = F.col("size") - F.ceil(F.col("size") * percent / 100) + 1
    fewer = F.col("size") - F.ceil(F.col("size") * (2 * percent) / (100 + percent)) + 1
    every = Window.partitionBy("node")
    ranked = ranked.withColumn("__i", F.row_number().over(order)).withColumn("shared", F.count_if(F.col("n") > 1).over(every)).withColumn("weight", F.sum(F.log2("n")).over(every))
    ranked = ranked.where((F.col("__i") <= need) & (F.col("n") > 1))
    return ranked.select("key", "node", "size", (F.col("__i") <= fewer).alias("indexed"), "shared", "weight")


def similar_groups(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, node, component_id (smallest doc_id reachable)."""
    signed = materialize(_shingled(docs, k, id_col, text_col, False), "similar")
    nodes = signed.groupBy("node").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n"), F.any_value("size").alias("size"), F.any_value("fp").alias("fp"), F.any_value("bands").alias("bands"))
    nodes = materialize(nodes, "similar-nodes")

    by_fp = materialize(nodes.groupBy("fp").agg(F.min("node").alias("first"), F.count(F.lit(1)).alias("n")), "similar-fps")
    same = join_by_key(nodes.select("fp", "node"), by_fp, ["fp"], "n", ["node"]).where("node <> first").select(F.col("first").alias("a"), F.col("node").alias("b"))
    named = by_fp.select("fp", "first")
    links = near_links(by_fp).join(named.select(F.col("fp").alias("a"), F.col("first").alias("x")), "a").join(named.select(F.col("fp").alias("b"), F.col("first").alias("y")), "b")
    by_bits = links.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))

    rows = nodes.select("node", "size", F.explode("bands").alias("key"), F.lit(True).alias("indexed"), F.col("size").cast("long").alias("shared"))
    pairs = materialize(_stars(rows, percent).union(same).union(by_bits).distinct(), "similar-pairs")
    shared = rows.groupBy("key").agg(F.min("node").alias("r"), F.max("node").alias("s")).where("r < s").select("key")
    rows = materialize(rows.join(shared, "key", "left_semi"), "similar-hits")

    wanted = rows.select("node").union(pairs.select("a")).union(pairs.select("b")).distinct()
    ids = wanted.join(nodes.select("node", "least"), "node").select(F.col("least").alias("__least")).distinct()
    texts = docs.join(ids, F.col(id_col).cast("long").eqNullSafe(F.col("__least")), "left_semi")
    sets = _shingled(texts, k, id_col, text_col, True).join(wanted, "node", "left_semi")
    sets = materialize(sets.groupBy("node").agg(F.any_value("grams").alias("grams")), "similar-sets")

    found = materialize(_verified(pairs, sets, percent), "similar-links")
    found, split = _settled(rows, found, sets, percent)
    few, crowd = split.where(F.col("n") <= CROWD), split.where(F.col("n") > CROWD)
    links = found.union(materialize(_verified(_across(few, percent), sets, percent), "similar-links"))
    if not crowd.isEmpty():
        rare = materialize(_rarest(sets.join(crowd.select("node").distinct(), "node", "left_semi"), percent), "similar-rare")
        links = materialize(links.union(_verified(_stars(rare, percent), sets, percent)), "similar-links")
        links, rest = _settled(rare, links, sets, percent)
        links = links.union(materialize(_verified(_across(rest, percent), sets, percent), "similar-links"))
    roots = materialize(connected_components(links), "similar-roots")
    by_node = component_names(nodes.select("node", "least", "n"), "node", roots)
    discard(rows, pairs, split, sets, roots, by_fp)
    return join_by_key(signed.select("doc_id", "node"), by_node, ["node"], "n", ["doc_id"]).select("doc_id", "node", "component_id")
