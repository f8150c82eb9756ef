"""Operators against brute force, and on nulls, empties, ties, repeats and clashing names."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from conftest import DATA

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [
    (0, None, "en", "a", 0), (1, "", "en", "a", 0), (2, "a b c", "en", None, 5), (3, "a b c", "en", None, 5),
    (3, "a b c", "en", None, 5), (4, "x" * 5000, "de", "b", 5000), (5, "Äö <|im_end|> \n\n z", None, "b", None), (None, "lost", "en", "a", 4),
]


def odd_docs(spark, rows=ODD):
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for extra in ("h", "sha", "size", "bin", "fp", "rate", "score", "pid"):  # names that operators use inside
        df = df.selectExpr("*", f"'x' as {extra}")
    return df


def low(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


# ---- exact dedup


def test_exact_dedup_odd_rows(spark):
    from zonal.llm.exact_dedup import drop_exact_duplicates, exact_groups

    got = exact_groups(odd_docs(spark), keep="largest").collect()
    assert len(got) == len(ODD)
    assert {(r.doc_id, r.keep_id, r.group_size, r.kept) for r in got if r.doc_id in (0, 1, 2, 3)} == {(0, 1, 2, False), (1, 1, 2, True), (2, 3, 3, False), (3, 3, 3, True)}
    assert drop_exact_duplicates(odd_docs(spark)).where("doc_id in (2, 3)").select("doc_id").distinct().collect()[0][0] == 2
    assert exact_groups(odd_docs(spark, [])).count() == 0


def test_exact_dedup_survives_hash_collisions(spark):
    from pyspark.sql import functions as F

    from zonal.llm.exact_dedup import exact_groups

    rows = [(i, f"t{i % 7}", "", "", 0) for i in range(100)]
    got = exact_groups(odd_docs(spark, rows), hasher=lambda c: F.lit(b"one")).collect()
    assert all(r.keep_id == r.doc_id % 7 for r in got)


# ---- mixing


def fill_up(size: dict, weight: dict, share=1.5, cap=2) -> dict:
    """Targets by plain iteration: share out by weight, cap, reshare."""
    target, open_, left = {}, set(size), share * sum(size.values())
    while open_:
        total = sum(weight[s] for s in open_)
        over = {s for s in open_ if left * weight[s] / total > cap * size[s]}
        if not over:
            return target | {s: left * weight[s] / total for s in open_}
        for s in over:
            target[s] = float(cap * size[s])
            left -= target[s]
        open_ -= over
    return target


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_mixing_targets(spark, sf):
    from zonal.llm.mixing import mix

    docs = spark.read.parquet(f"{DATA}/{sf}/documents.parquet")
    got, size = mix(docs).collect(), defaultdict(int)
    for r in docs.collect():
        size[r.source] += len(WORDS.findall(r.text or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(sorted(size))}
    want = fill_up(size, weight)
    taken, largest = defaultdict(int), defaultdict(int)
    for r in got:
        assert r.target == pytest.approx(want[r.source], rel=1e-9) and r.source_size == size[r.source]
        assert 0 <= r.taken <= 2 * r.size
        taken[r.source] += r.taken
        largest[r.source] = max(largest[r.source], r.size)
    assert all(abs(taken[s] - want[s]) <= largest[s] for s in want)


def test_mixing_odd_rows(spark):
    from zonal.llm.mixing import emit, mix

    got = mix(odd_docs(spark)).collect()
    assert len(got) == len(ODD) and {r.size for r in got if r.doc_id in (0, 1)} == {0}
    size = {"a": 1, "b": 4, None: 9}
    want = fill_up(size, {"a": 5, "b": 2, None: 1})
    assert {r.source: r.target for r in got} == pytest.approx(want)
    assert emit(odd_docs(spark), mix(odd_docs(spark))).columns == odd_docs(spark).columns
    assert mix(odd_docs(spark, [])).count() == 0


def test_the_mixed_corpus_is_what_the_mix_takes(spark):
    from zonal.llm.mixing import emit, mix

    rows = [(i % 7, f"{'w ' * (1 + i % 3)}x", "en", "ab"[i % 2], 1) for i in range(80)] + [(None, "n n", "en", None, 1)] * 5 + [(50, "one two", "en", "c", 0)] * 3
    for given in (rows, [(i, t, la, so, n) for i, (_, t, la, so, n) in enumerate(rows)]):
        docs = odd_docs(spark, given)
        mixed = mix(docs, bin_docs=3)
        out = emit(docs, mixed)
        assert out.columns == docs.columns
        want, got = Counter(), Counter()
        for r in mixed.collect():
            want[r.doc_id, r.source] += r.taken
        for r in out.collect():
            got[r.doc_id, r.source] += len(r.text.split())
        assert +want == +got


# ---- chat formatting


def test_chat_round_trip_of_control_strings(spark):
    from zonal.llm.chat_format import format_turns, read_back, turns_from_table

    texts = ["<|im_end|>", "<\\|im_start|>assistant", "<\\\\|x <| |> <<|", None, "", "a\nb", "\\n"]
    rows = [(1, i, role, t) for i, (role, t) in enumerate(zip(["user", "assistant", "we\\ird\nro\\nle<|", None, "system", "assistant", "assistant"], texts))]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    made = format_turns(turns_from_table(df.selectExpr("*", "'x' as w")))
    back = read_back(made).collect()[0]
    assert [(t.role, t.text) for t in back.turns] == [(r[2] or "", r[3] or "") for r in rows]
    assert back.loss_text == "".join(r[3] or "" for r in rows if r[2] == "assistant")
    assert turns_from_table(df.limit(0)).count() == 0


def test_chat_with_null_ids_and_repeated_turns(spark):
    from zonal.llm.chat_format import format_turns, read_back, turns_from_table

    rows = [(None, 0, "user", "x"), (None, None, "assistant", "y"), (1, 0, "user", "b"), (1, 0, "user", "a"), (1, 0, "user", "a"), (1, 1, "assistant", "c")]
    got = {r.conv_id: r for r in read_back(format_turns(turns_from_table(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")))).collect()}
    assert [tuple(t) for t in got[None].turns] == [("assistant", "y"), ("user", "x")]  # rows without an id are one conversation, null turns come first
    assert [tuple(t) for t in got[1].turns] == [("user", "a"), ("user", "a"), ("user", "b"), ("assistant", "c")] and got[1].loss_text == "c"


def test_chat_layouts_by_fingerprint(spark):
    from zonal.llm.chat_format import turns_from_json, turns_from_table

    rows = [
        (1, '{"messages":[{"role":"user","content":"q"},{"role":"assistant","content":"a"}],"id":3}'),
        (2, '{"conversations":[{"from":"human","value":"q"},{"from":"gpt","value":"a"}]}'),
        (3, '{"instruction":"q","output":"a"}'), (4, '{"prompt":"q","response":"a","extra":{"x":1}}'),
        (5, '{"question":"q","answer":"a"}'), (6, '{"instruction":"q","input":"i","output":"a"}'), (7, '{"odd":1}'), (8, "not json"), (9, None),
    ]
    got = {r.conv_id: r for r in turns_from_json(spark.createDataFrame(rows, "k bigint, j string"), "j", "k").collect()}
    qa = [("user", "q"), ("assistant", "a")]
    assert all([tuple(t) for t in got[i].turns] == qa for i in (1, 2, 3, 4, 5))
    assert [tuple(t) for t in got[6].turns] == [("user", "q\n\ni"), ("assistant", "a")]
    assert all(got[i].turns is None for i in (7, 8, 9))
    table = spark.createDataFrame([("q", "a", 1)], "prompt string, completion string, other int")
    assert [tuple(t) for t in turns_from_table(table).collect()[0].turns] == qa


# ---- line dedup


def test_line_dedup_odd_rows(spark):
    from pyspark.sql import functions as F

    from zonal.llm.line_dedup import drop_boilerplate, host_of

    rows = [(i, "http://h.x/a", f"menu\nown {i}\n\n menu ") for i in range(6)] + [(7, None, None), (8, "bad", ""), (9, "http://H.X/b", "once")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").selectExpr("*", "'x' as host", "'x' as line", "'x' as lines")
    got = {r.page_id: r for r in drop_boilerplate(df, host_of(F.col("url")), "page_id", "html", 0.5, 3).collect()}
    assert got[0].html == "own 0\n" and got[0]["__n_dropped"] == 2 and got[9].html == "once"
    assert got[7].html is None and got[8].html == "" and len(got) == 9


# ---- quality classifier


def test_quality_on_held_out_rows(spark):
    from zonal.llm.queries import op2_quality_classifier

    got = {r.doc_id: r for r in op2_quality_classifier(spark, f"{DATA}/sf0.1").collect()}
    right = total = 0
    for r in spark.read.parquet(f"{DATA}/sf0.1/labels.parquet").collect():
        g = got[r.doc_id]
        assert g.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2)
        if g.held_out:
            right, total = right + (g.predicted == r.quality), total + 1
    assert total > 900 and right / total > 0.97
    assert all(0 <= g.score <= 1 and g.predicted == (g.score >= 0.7) for g in got.values())


def test_quality_gradients_and_odd_rows(spark):
    from zonal.llm.quality import AttentionModel, encode, fit, keep_good, score

    labels = spark.createDataFrame([(2, 1), (4, 0), (5, None)], "doc_id bigint, quality int")
    model = fit(odd_docs(spark), labels)
    got = score(odd_docs(spark), model).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 for r in got)
    assert fit(odd_docs(spark), labels.limit(0)) is None and score(odd_docs(spark), None).collect()[0].score == 0.5
    assert keep_good(odd_docs(spark), model).columns == odd_docs(spark).columns
    assert AttentionModel().attention(encode("word " * 500)).sum() == pytest.approx(1)


def test_quality_fit_is_bounded_and_gradients_are_right():
    from zonal.llm.quality import N_FEATURES, AttentionModel, encode, spread

    bag = encode(" ".join(f"w{i}" for i in range(5000)))
    assert len(spread(bag, 10)) == 10 and (spread(bag, 10)[[0, -1]] == bag[[0, -1]]).all() and spread(bag, 10**6) is bag
    r = np.random.default_rng(0)
    bags, labels = [r.standard_normal((n, N_FEATURES)).astype(np.float32) for n in (1, 3, 5, 2)], np.array([1.0, 0, 1, 0])

    def loss(m):
        y = m.scores(bags)
        return float(-(labels * np.log(y) + (1 - labels) * np.log(1 - y)).mean())

    m = AttentionModel(hidden=6, gate=4)
    g = m.gradients(*m._scaled(bags), labels)
    for name, p in m.p.items():
        for at in list(np.ndindex(p.shape))[:: max(1, p.size // 7)]:
            old, eps = p[at], 1e-5
            p[at] = old + eps
            up = loss(m)
            p[at] = old - eps
            down = loss(m)
            p[at] = old
            assert g[name][at] == pytest.approx((up - down) / (2 * eps), rel=2e-3, abs=1e-6), (name, at)


# ---- SimHash


def test_thresholds_are_least_cost():
    from itertools import product

    from zonal.llm.simhash import allocate

    r = np.random.default_rng(1)
    for m, total in ((3, 0), (2, 1), (4, -1)):
        counts = [np.cumsum(r.random((50, 3)) * [[0, 1, 1]], axis=1) for _ in range(m)]
        got = allocate(counts, total)
        for q in range(50):
            cost = lambda t: sum(counts[i][q, x + 1] for i, x in enumerate(t))  # noqa: B023, E731
            best = min(cost(t) for t in product((-1, 0, 1), repeat=m) if sum(t) == total)
            assert got[q].sum() == total and cost(got[q]) == pytest.approx(best)


@pytest.mark.parametrize(("parts", "hot"), [(3, 64), (3, 0), (2, 8), (4, 4)])
def test_near_links_join_all_pairs(spark, parts, hot):
    from zonal.llm.components import connected_components
    from zonal.llm.simhash import near_links

    rnd = random.Random(parts)
    base = [rnd.getrandbits(64) for _ in range(40)]
    fps = {0, (1 << 64) - 1, *base} | {b ^ (1 << rnd.randrange(64)) ^ (1 << rnd.randrange(64)) ^ (1 << rnd.randrange(64) if rnd.random() < 0.5 else 0) for b in base for _ in range(8)}
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    reps = spark.createDataFrame([(f,) for f in signed], "fp bigint")
    links = near_links(reps, 2, parts, hot)
    assert all(((a ^ b) & ((1 << 64) - 1)).bit_count() <= 2 for a, b in links.collect())
    roots = dict(map(tuple, connected_components(links).collect()))
    root = {f: f for f in signed}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in signed:
        for b in signed:
            if a < b and ((a ^ b) & ((1 << 64) - 1)).bit_count() <= 2:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    assert all(roots.get(f, f) == find(f) for f in signed)


def test_simhash_odd_rows(spark):
    import xxhash

    from zonal.llm.simhash import fingerprint, near_duplicates

    got = {r.doc_id: r for r in near_duplicates(odd_docs(spark)).collect()}
    assert got[0].fp == got[1].fp == 0 and got[1].component_id == 0 and got[3].component_id == 2
    assert near_duplicates(odd_docs(spark, [])).count() == 0
    assert fingerprint(b"A b") == xxhash.xxh64_intdigest("a b", 42)


def test_components_of_chains_and_stars(spark):
    from zonal.llm.components import connected_components

    rnd = random.Random(4)
    links = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 300)]
    rnd.shuffle(links)
    got = dict(map(tuple, connected_components(spark.createDataFrame(links, "a bigint, b bigint").repartition(8)).collect()))
    assert got == {**{i: 0 for i in range(1, 201)}, **{1000 + i: 1000 for i in range(1, 300)}}


# ---- language model


def plain_kneser_ney(train, order):
    """Probabilities by dictionaries, for any order."""
    grams = [Counter() for _ in range(order + 1)]
    for t in train:
        seq = ["<s>"] * (order - 1) + t
        grams[order].update(tuple(seq[i : i + order]) for i in range(len(t)))
    for k in range(order - 1, 0, -1):
        grams[k].update(g[1:] for g in grams[k + 1])

    def discount(c):
        n1, n2, n3, n4 = (sum(1 for v in c.values() if v == i) for i in (1, 2, 3, 4))
        y = n1 / (n1 + 2 * n2) if n1 and n2 else 0.5
        d = [1 - 2 * y * n2 / n1 if n1 and n2 else 0.5, 2 - 3 * y * n3 / n2 if n2 and n3 else 1.0, 3 - 4 * y * n4 / n3 if n3 and n4 else 1.5]
        return [0.0] + [min(max(x, 0.05), i + 1.0) for i, x in enumerate(d)]

    d = [None] + [discount(grams[k]) for k in range(1, order + 1)]
    total, kinds = [defaultdict(int) for _ in range(order + 1)], [defaultdict(lambda: [0, 0, 0, 0]) for _ in range(order + 1)]
    for k in range(1, order + 1):
        for g, c in grams[k].items():
            total[k][g[:-1]] += c
            kinds[k][g[:-1]][min(c, 3)] += 1

    def p(seq):
        out = 1 / (len(grams[1]) + 1)
        for k in range(1, order + 1):
            ctx = seq[len(seq) - k : -1]
            if total[k].get(ctx):
                c = grams[k].get(seq[len(seq) - k :], 0)
                out = (max(c - d[k][min(c, 3)], 0) + sum(d[k][i] * kinds[k][ctx][i] for i in (1, 2, 3)) * out) / total[k][ctx]
        return out

    return p, grams


@pytest.mark.parametrize("order", [2, 3])
def test_language_model_equals_dictionaries(spark, order):
    from zonal.llm.language_model import held_out, score, train

    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")
    model = train(docs.where(~held_out(F.col("doc_id"))), order)
    got = {r.doc_id: r for r in score(docs, model).collect()}
    texts = {r.doc_id: [*WORDS.findall(low(r.text)), "</s>"] for r in docs.collect()}
    fit = [t for d, t in texts.items() if zlib.crc32(str(d).encode()) % 10]
    p, grams = plain_kneser_ney(fit, order)
    c = Counter(w for t in fit for w in t)
    n, v = sum(c.values()), len(c)
    for d, t in texts.items():
        seq = ("<s>",) * (order - 1) + tuple(t)
        want = sum(math.log10(p(seq[i : i + order])) for i in range(len(t)))
        assert got[d].score == pytest.approx(want, rel=1e-9)
        assert got[d].base_score == pytest.approx(sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t), rel=1e-9)
        assert (got[d].n_tokens, got[d].n_known, got[d].train_tokens) == (len(t), sum(w in c for w in t), n)
    some = ("<s>",) * (order - 1) if order > 2 else ("<s>",)
    assert sum(p((*some, w)) for (w,) in grams[1]) + p((*some, "never seen")) == pytest.approx(1)


def test_language_model_odd_rows(spark):
    from zonal.llm.language_model import score, train

    got = {r.doc_id: r for r in score(odd_docs(spark), train(odd_docs(spark))).collect()}
    assert got[0].n_tokens == got[1].n_tokens == 1 and all(r.score < 0 for r in got.values())
    none = score(odd_docs(spark), train(odd_docs(spark, []))).collect()
    assert all(r.n_known == 0 and math.isfinite(r.score) for r in none)


def test_word_hashes_split_long_texts():
    from zonal.llm import language_model as lm

    text = ("Word0 wORD1\t\n x" * 9).encode() + b" tail"
    old, lm.PIECE = lm.PIECE, 16
    try:
        short = np.concatenate(list(lm.token_blocks([text, b"", b"y"])))
    finally:
        lm.PIECE = old
    whole = np.concatenate(list(lm.token_blocks([text, b"", b"y"])))
    assert np.array_equal(short, whole) and (whole == lm.END).sum() == 3
    assert len(set(whole.tolist())) == len({*text.lower().split(), b"", b"y"})


# ---- packing


def test_packing_is_a_partition_of_the_ids(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    from zonal.llm.packing import pack

    docs = spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")
    got = pack(docs, with_ids=True).collect()
    bpe = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    pieces, fill = defaultdict(list), defaultdict(list)
    for r in got:
        pieces[r.doc_id].append(r)
        fill[r.sequence_id].append(r)
    for d in docs.collect():
        ids = np.array([*bpe.encode(d.text or "", add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for r in sorted(pieces[d.doc_id], key=lambda r: r.start):
            assert (r.start, r.doc_tokens) == (at, len(ids))
            assert r.ids == ids[at : at + r.length].tobytes() and r.ids_crc32 == zlib.crc32(r.ids)
            at += r.length
        assert at == len(ids)
    padding = 0
    for rs in fill.values():
        rs.sort(key=lambda r: r.offset)
        assert [r.offset for r in rs] == [sum(x.length for x in rs[:i]) for i in range(len(rs))]
        n = sum(r.length for r in rs)
        assert n <= 2048
        padding += 0 if n & (n - 1) == 0 else 2048 - n
    assert padding <= 2048 * docs.rdd.getNumPartitions()
    assert pack(odd_docs(spark)).where("doc_id = 0").collect()[0].doc_tokens == 1
    assert pack(odd_docs(spark, [])).count() == 0


# ---- suffix dedup


def test_suffix_order_equals_sorting():
    from zonal.llm.suffix_dedup import suffix_order

    rnd = random.Random(2)
    for _ in range(2000):
        t = [rnd.randint(1, rnd.choice([1, 2, 4])) for _ in range(rnd.randint(1, 40))]
        assert suffix_order(t) == sorted(range(len(t)), key=lambda i: t[i:])


def plain_removal(docs, length):
    first, out = {}, {}
    for d, b in sorted(docs):
        gone = bytearray(len(b))
        for j in range(len(b) - length + 1):
            if first.setdefault(b[j : j + length], d) < d:
                gone[j : j + length] = b"\1" * length
        kept = bytes(c for c, g in zip(b, gone) if not g)
        spans = sum(1 for i, g in enumerate(gone) if g and not (i and gone[i - 1]))
        out[d] = (len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest())
    return out


def test_suffix_dedup_equals_brute_force(spark):
    from zonal.llm.queries import op6_suffix_dedup

    docs = [(r.doc_id, (r.text or "").encode()) for r in spark.read.parquet(f"{DATA}/sf0.01/documents.parquet").collect()]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in op6_suffix_dedup(spark, f"{DATA}/sf0.01").collect()}
    assert got == plain_removal(docs, 50)


def test_suffix_dedup_periodic_and_odd_rows(spark):
    from zonal.llm.suffix_dedup import remove_repeats

    rnd = random.Random(7)
    part = ["ab" * 40, "a" * 300, "".join(rnd.choice("abc") for _ in range(120)), "é" * 60, "xyz" * 50]
    texts = [(i, "".join(rnd.choice(part)[rnd.randrange(20) :] for _ in range(rnd.randint(0, 4)))) for i in range(60)]
    rows = [(i, t, "", "", 0) for i, t in texts] + [(77, None, "", "", 0)]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in remove_repeats(odd_docs(spark, rows)).collect()}
    assert got == plain_removal([(i, t.encode()) for i, t in texts] + [(77, b"")], 50)
    assert remove_repeats(odd_docs(spark)).count() == len(ODD) and remove_repeats(odd_docs(spark, [])).count() == 0
    with_text = remove_repeats(odd_docs(spark, rows), with_text=True).where("kept is not null").collect()
    assert all(hashlib.sha256(r.kept).hexdigest() == r.kept_sha256 and len(r.spans) == r.n_spans for r in with_text)


# ---- nearest neighbours


def test_nearest_recall_and_scores(spark):
    from zonal.llm.queries import op9_nearest_neighbours

    table = {r.vec_id: np.array(r.embedding, float) for r in spark.read.parquet(f"{DATA}/sf0.1/embeddings.parquet").collect()}
    ids = np.array(sorted(table))
    x = np.stack([table[i] for i in ids.tolist()])
    found = defaultdict(list)
    for r in op9_nearest_neighbours(spark, f"{DATA}/sf0.1").collect():
        found[r.query_id].append(r)
        assert r.score == pytest.approx(float(table[r.query_id] @ table[r.vec_id]), rel=1e-12)
    hits = 0
    for q, rs in found.items():
        assert [r.rank for r in sorted(rs, key=lambda r: (-r.score, r.vec_id))] == list(range(1, 21)) and q not in {r.vec_id for r in rs}
        score = np.where(ids == q, -np.inf, x @ table[q])
        hits += len(set(ids[np.lexsort((ids, -score))[:20]].tolist()) & {r.vec_id for r in rs})
    assert len(found) == 100 and hits / 2000 >= 0.95


def test_nearest_odd_rows(spark):
    from pyspark.sql import functions as F

    from zonal.llm.nearest import nearest

    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.5, 0.5]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (6, [1.0, None]), (7, [1.0]), (20, [0.0, 2.0]), (8, [float("inf"), 0.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").selectExpr("*", "'x' as v", "'x' as q")
    got = nearest(df, F.col("vec_id") % 20 == 0, k=20).collect()
    assert [(r.query_id, r.rank, r.vec_id) for r in sorted(got)] == [(0, 1, 1), (0, 2, 2), (0, 3, 20), (20, 1, 2), (20, 2, 0), (20, 3, 1)]
    assert nearest(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


def test_indexed_keys_are_found():
    from zonal.llm import language_model as lm

    r = np.random.default_rng(2)
    keys = np.unique(r.integers(0, 1 << lm.KEY_BITS, 5000, dtype=np.uint64))
    there, f = keys[::2], lm.indexed(keys[::2])
    ok, place = lm.locate(f, keys)
    assert np.array_equal(np.flatnonzero(ok), np.arange(0, len(keys), 2)) and np.array_equal(there[place], there)
    assert not lm.locate(lm.indexed(keys[:0]), keys)[0].any()
    for n in (0, 1, 300):
        words = r.integers(0, 1 << 40, (3, n), dtype=np.uint64)
        words, count = lm.squash(np.concatenate([words, words], axis=1), np.ones(2 * n, np.int64))
        assert words.shape[1] == n and (count == 2).all() and (n == 0 or (words[0][1:] >= words[0][:-1]).all())
        got = lm.blocks(words, count, np.zeros(words.shape[1], np.int32), 1)
        assert got.num_rows == (n > 0)
        if n:
            back, times = lm.unblock(n, got.column(2)[0].as_py(), 3)
            assert np.array_equal(back, words) and np.array_equal(times, count)


def test_language_model_with_hot_contexts_and_more_buckets(spark, monkeypatch):
    """Contexts spread over buckets, and any number of buckets, give the same probabilities."""
    from zonal.llm import language_model as lm

    docs = spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")
    want = {r.doc_id: r.score for r in lm.score(docs, lm.train(docs, 3, buckets=8)).collect()}
    monkeypatch.setattr(lm, "HOT_SHARE", 0.002)
    model = lm.train(docs, 3, buckets=300)
    assert all(len(h) for h in model.hot[2:]) and any(model.hot_stats[2:])
    assert {r.doc_id: r.score for r in lm.score(docs, model).collect()} == pytest.approx(want, rel=1e-12)
