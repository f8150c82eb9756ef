"""Departures from the contracts that given tables don't show."""

import random
import re

import numpy as np
import pytest
from conftest import DATA
from test_operators import odd_docs, plain_removal


def test_added_token_of_the_vocabulary(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    from zonal.llm.packing import pack

    bpe = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = ["a <|endoftext|> b", "<|endoftext|><|endoftext|>", "x<|endoftext|", "<|endoftext|>\n\n y  <|im_end|>", "<|ENDOFTEXT|>", "é<|endoftext|>ß 'll"]
    rows = pack(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"), with_ids=True).collect()
    for i, t in enumerate(texts):
        got = b"".join(r.ids for r in sorted((r for r in rows if r.doc_id == i), key=lambda r: r.start))
        assert np.frombuffer(got, "<u4").tolist() == [*bpe.encode(t, add_special_tokens=False).ids, 1]


def test_step_groups_and_tiers(spark):
    from zonal.llm.packing import TIERS, pack

    docs = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")
    pieces = pack(docs, step_tokens=4096).collect()
    tier, group, fill = {}, {}, {}
    for r in pieces:
        assert tier.setdefault(r.sequence_id, r.tier) == r.tier and group.setdefault(r.sequence_id, r.step_group) == r.step_group
        fill[r.sequence_id] = fill.get(r.sequence_id, 0) + r.length
    assert set(tier.values()) <= set(TIERS) and all(fill[s] <= tier[s] for s in fill)
    for g in set(group.values()):  # a group holds one tier, and no more than its tokens
        mine = [s for s in group if group[s] == g]
        assert len({tier[s] for s in mine}) == 1 and sum(tier[s] for s in mine) <= 4096


def test_suffix_dedup_with_repeated_ids(spark):
    from zonal.llm.suffix_dedup import remove_repeats

    rnd = random.Random(3)
    words = ["".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(2, 9))) for _ in range(60)]
    long = lambda n: " ".join(rnd.choice(words) for _ in range(n))
    a = long(14)
    rows = [(1, a), (2, f"zzz {a} tail"), (2, long(30)), (2, f"other {a}"), (3, a), (3, long(20)), (None, a), (4, f"{a} {a}")]
    rows += [(i % 5, f"{long(3)} {rnd.choice([a, long(12)])} {long(3)}") for i in range(40)]
    got = remove_repeats(odd_docs(spark, [(i, t, "", "", 0) for i, t in rows]), with_text=False).collect()
    want = []
    known = [(i, t.encode()) for i, t in rows if i is not None]
    first = {}
    for i, b in sorted(known):
        for j in range(len(b) - 49):
            first.setdefault(b[j : j + 50], i)
    for i, t in rows:
        b, gone = t.encode(), bytearray(len(t.encode()))
        for j in range(len(b) - 49) if i is not None else ():
            if first[b[j : j + 50]] < i:
                gone[j : j + 50] = b"\1" * 50
        want.append((i, len(b), sum(gone)))
    assert sorted(((r.doc_id, r.n_bytes, r.n_removed) for r in got), key=repr) == sorted(want, key=repr)


def plain_fingerprint(text):
    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    grams = [" ".join(words[i : i + 3]) for i in range(max(len(words) - 2, 1))] if words else []
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprints_equal_a_plain_count(spark):
    from zonal.llm.queries import op3_simhash_near_dedup

    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{DATA}/sf0.001/documents.parquet").collect()}
    got = {r.doc_id: r for r in op3_simhash_near_dedup(spark, f"{DATA}/sf0.001").collect()}
    fp = {d: plain_fingerprint(t) for d, t in docs.items()}
    assert {d: r.fingerprint for d, r in got.items()} == {d: f"{x:016x}" for d, x in fp.items()}
    root = {d: d for d in fp}

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    for a in fp:
        for b in fp:
            if a < b and (fp[a] ^ fp[b]).bit_count() <= 2:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    assert {d: r.component_id for d, r in got.items()} == {d: find(d) for d in fp}


@pytest.mark.parametrize("parts", [3, 2, 1])
def test_a_crowded_sketch_keeps_the_partitions(spark, parts):
    """Bins with thousands of fingerprints each steer costs only: rows stay in the partitions."""
    from zonal.llm.components import connected_components
    from zonal.llm.simhash import Scheme, group_bits, near_links, part_keys, partitions_for

    assert [partitions_for(n) for n in (0, 10**6, 10**8, 10**10, 10**12)] == [3, 3, 2, 2, 1]
    r = np.random.default_rng(parts)
    fps = r.integers(0, 1 << 63, 1500, dtype=np.uint64)
    fps = np.unique(np.concatenate([fps, fps[:300] ^ np.uint64(5), fps[300:600] ^ np.uint64(1 << 40)]))
    grouped = group_bits(fps, parts)
    scheme = Scheme(grouped, np.full((parts, 2), 10**6), 2)
    part, key, role, who = scheme.rows(fps[:50])
    assert set(part.tolist()) == set(range(parts))
    own = part_keys(fps[:50], grouped)
    assert {(i, int(k)) for i in range(parts) for k in own[i].view(np.int64)} <= set(zip(part.tolist(), key.tolist(), strict=True))
    reps = spark.createDataFrame([(x,) for x in fps.view(np.int64).tolist()], "fp bigint")
    got = dict(map(tuple, connected_components(near_links(reps, 2, parts, bins=2)).collect()))
    near = {int(x) for x in fps}
    pairs = [(a, b) for a in near for f in (5, 1 << 40) if (b := a ^ f) in near]
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    assert pairs and all(got.get(signed(a), signed(a)) == got.get(signed(b), signed(b)) for a, b in pairs)
