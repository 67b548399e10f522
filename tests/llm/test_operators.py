"""The ten operators against brute force, exact round trips and held-out accuracy, with the awkward cases of each."""

import hashlib
import math
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from flowlens.llm import binary_output, components, hamming, matroska, mixing, near_dup, packing, quality, shingles, substring_dedup, suffix_array, tokens, toxicity, url_filter
from flowlens.llm.common import table
from flowlens.llm.registry import ORACLES, QUERIES

from ..conftest import SF, rows_of

DOCS = "doc_id long, text string, source string, rep string, size int, key string, _spans int, cell int"


def docs_frame(spark, texts, sources=None):
    """Documents with extra columns whose names the operators use inside."""
    return spark.createDataFrame([(i, t, (sources or ["a", "b", None])[i % len(sources or "abc")], "x", 7, "k", 3, 1) for i, t in enumerate(texts)], DOCS)


def prose(rng, n, vocabulary=400):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


AWKWARD = [None, "", "   \n\t", "one", "one two three", "été \U0001f600 naïve", "A\x0bB\x0cC", "x" * 5000, "ab " * 400]


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, duck, name):
    got, want = QUERIES[name](spark, SF).toPandas(), duck.execute(ORACLES[name]).fetchdf()
    assert rows_of(got) == rows_of(want)


# 1


def test_packed_ids_hold_every_token_once(spark):
    rng = random.Random(1)
    texts = AWKWARD + [prose(rng, rng.randrange(1, 3000)) for _ in range(40)] + ["same text"] * 5
    df = docs_frame(spark, texts)
    encode = tokens.encoder(tokens.default_vocabulary())
    parts = defaultdict(dict)
    for cap, buffer in ((256, 4000), (2048, 10**6)):
        parts.clear()
        for r in binary_output.pack_documents(df, cap, buffer_tokens=buffer).collect():
            ids = np.frombuffer(r["ids"], "<u2")
            assert len(ids) == r["n_tokens"] == r["cu_seqlens"][-1] <= cap and r["position_resets"] == r["cu_seqlens"][:-1]
            assert [p for p, v in enumerate(binary_output.position_ids(r["cu_seqlens"])) if v == 0] == r["position_resets"]
            for d, s, a, b in zip(r["doc_ids"], r["starts"], r["cu_seqlens"], r["cu_seqlens"][1:]):
                assert s not in parts[d]
                parts[d][s] = ids[a:b]
        for i, t in enumerate(texts):
            whole = np.concatenate([parts[i][s] for s in sorted(parts[i])])
            assert whole.tolist() == [*encode(t or "").tolist(), 50256]
    assert binary_output.pack_documents(df.limit(0)).count() == 0


def test_segment_tree_gives_best_fit():
    rng = random.Random(2)
    for _ in range(200):
        sizes, cap = [rng.randrange(1, 51) for _ in range(rng.randrange(60))], 50
        got = binary_output.best_fit_decreasing(sizes, cap)
        free = []
        for s in sorted(sizes, reverse=True):
            fits = [i for i, f in enumerate(free) if f >= s]
            if fits:
                free[min(fits, key=lambda i: free[i])] -= s
            else:
                free.append(cap - s)
        assert len(got) == len(free) and all(sum(sizes[i] for i in b) <= cap for b in got) and sorted(i for b in got for i in b) == list(range(len(sizes)))


def test_both_libraries_give_the_same_ids():
    fast, slow = tokens.encoder(tokens.default_vocabulary()), tokens.encoder(tokens.default_vocabulary("byte_bpe_50k.json"))
    rng = random.Random(3)
    for _ in range(300):
        t = "".join(chr(rng.choice([rng.randrange(32, 127), rng.randrange(9, 14), rng.randrange(160, 0x3000), 0x1F600])) for _ in range(rng.randrange(200)))
        assert fast(t).tolist() == slow(t).tolist()
    for t in [x or "" for x in AWKWARD] + ["a<|endoftext|>b", "it's we'll  \n\n  x"]:
        assert fast(t).tolist() == slow(t).tolist()


def test_long_runs_of_blanks_have_the_ids_of_the_json_file():
    fast, slow = tokens.encoder(tokens.default_vocabulary()), tokens.encoder(tokens.default_vocabulary("byte_bpe_50k.json"))
    n = tokens.LONG_RUN
    for blank in (" ", "\n", "\t", " \n\t", "\u3000 ", "\x85"):
        run = blank * (n // len(blank) + 7)
        for t in (run, "a" + run, run + "b", "a" + run + "b c", run + "<|endoftext|>" + run + " x", "x  " + "y" * 10 + run + "9" + run + "\x1c" + run):
            assert fast(t).tolist() == slow(t).tolist()
    for blank in (" ", "\n", "\t"):
        assert len(fast("a" + blank * 2_000_000 + "b")) == len(slow("a" + blank * 2_000_000 + "b"))


def test_very_long_texts_are_packed(spark):
    texts = [" " * 2_000_000, "a" + "\n" * 1_500_000 + "b", "\t" * 1_100_000 + "x", "hello wörld 12 " * 333_000]
    df = docs_frame(spark, texts)
    slow = tokens.encoder(tokens.default_vocabulary("byte_bpe_50k.json"))
    whole = [slow(t) for t in texts]
    parts = defaultdict(dict)
    for r in binary_output.pack_documents(df).collect():
        ids = np.frombuffer(r["ids"], "<u2")
        for d, s, a, b in zip(r["doc_ids"], r["starts"], r["cu_seqlens"], r["cu_seqlens"][1:]):
            parts[d][s] = ids[a:b]
    for i, w in enumerate(whole):
        assert np.array_equal(np.concatenate([parts[i][s] for s in sorted(parts[i])])[:-1], w)
    pieces = packing.pack(packing.token_pieces(df)).collect()
    for i, w in enumerate(whole):
        ids = np.append(w, np.uint32(0)).astype("<u4")
        mine = sorted((r for r in pieces if r["doc_id"] == i), key=lambda r: r["piece"])
        assert sum(r["length"] for r in mine) == len(ids)
        assert all(zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"] for r in mine)


def test_id_width_follows_the_vocabulary(spark, tmp_path):
    import base64

    path = tmp_path / "byte_bpe_wide.tiktoken"
    lines = [base64.b64encode(bytes([k])) + b" %d" % (k if k != 97 else 70_000) for k in range(256)]
    path.write_bytes(b"\n".join(lines))
    assert tokens.largest_id(str(path)) == 70_000
    row = binary_output.pack_documents(spark.createDataFrame([(1, "ab")], "doc_id long, text string"), vocabulary=str(path)).first()
    assert np.frombuffer(row["ids"], "<u4").tolist() == [70_000, 98, 50256]


# 2


def brute_components(texts, num=75):
    table = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(table))
        sets.append({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set())
    up = list(range(len(texts)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                up[max(a, b)] = min(a, b)
    return [(len(s), find(i)) for i, s in enumerate(sets)]


def near_texts(rng, groups=6, size=14):
    out = []
    for _ in range(groups):
        base = prose(rng, 150).split()
        for _ in range(size):
            w = list(base)
            for _ in range(rng.randrange(0, 10)):
                w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
            out.append(" ".join(w))
    return out


@pytest.mark.parametrize("cell, hot", [(1024, 1 << 26), (4, 1 << 26), (1024, 0)])
def test_near_duplicates_equal_all_pairs(spark, monkeypatch, cell, hot):
    monkeypatch.setattr(near_dup, "CELL", cell)
    monkeypatch.setattr(near_dup, "HOT_PAIRS", hot)
    rng = random.Random(4)
    texts = near_texts(rng) + AWKWARD + ["One  Two\tthree", "one two three", "a b c d e"] * 2 + [prose(rng, 80) for _ in range(20)]
    rng.shuffle(texts)
    got = {r["doc_id"]: r for r in near_dup.near_duplicates(docs_frame(spark, texts)).collect()}
    for i, (n, c) in enumerate(brute_components(texts)):
        assert (got[i]["n_shingles"], got[i]["component_id"], got[i]["kept"]) == (n, c, c == i), i


def test_a_hot_bucket_of_unlinked_texts_meets_by_rare_shingles(spark, monkeypatch):
    monkeypatch.setattr(near_dup, "HOT_PAIRS", 100)
    rng = random.Random(20)
    common = prose(rng, 120)
    texts = [common + " " + prose(rng, 90, 10**6) for _ in range(150)]
    texts += [t + " and two words" for t in texts[:5]]
    got = {r["doc_id"]: r["component_id"] for r in near_dup.near_duplicates(docs_frame(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == [c for _, c in brute_components(texts)] == [*range(150), *range(5)]
    members = spark.createDataFrame([(i, i) for i in range(150)], "rep long, c long")
    groups = near_dup.rare_groups(members, docs_frame(spark, texts), near_dup.Params())
    assert groups.groupBy("k").count().agg(F.max("count")).first()[0] in (None, 2)


def test_near_duplicates_of_repeated_missing_and_no_rows(spark):
    df = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (None, "a b c d e f"), (5, None), (3, "a b c d e f")], "doc_id long, text string")
    got = sorted((r["doc_id"] or -1, r["component_id"], r["kept"]) for r in near_dup.near_duplicates(df).collect())
    assert got == [(-1, None, True), (1, 1, True), (1, 1, True), (3, 1, False), (5, 5, True)]
    assert near_dup.near_duplicates(df.limit(0)).count() == 0


def test_posterior_bounds():
    assert near_dup.posterior_tail(16, 16, 0.75) > 0.99 and near_dup.posterior_tail(0, 128, 0.75) < 1e-20
    bounds = near_dup.least_matches(near_dup.Params())
    assert bounds == sorted(bounds) and bounds[-1] < 96


def test_components_of_chains_stars_and_cliques(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, j) for j in range(101, 140)] + [(a, b) for a in range(200, 208) for b in range(200, a)] + [(7, 7), (None, 3)]
    got = {r["node"]: r["component"] for r in components.connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert {got[i] for i in range(41)} == {0} and {got[i] for i in range(100, 140)} == {100} and {got[i] for i in range(200, 208)} == {200}
    assert components.connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


# 3


def brute_targets(sizes):
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    w = {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}
    budget, fixed = 1.5 * sum(sizes.values()), {}
    while True:
        rest = [s for s in names if s not in fixed]
        if not rest:
            return fixed
        share = (budget - sum(fixed.values())) / sum(w[s] for s in rest)
        over = [s for s in rest if share * w[s] > 2 * sizes[s]]
        if not over:
            return fixed | {s: share * w[s] for s in rest}
        fixed |= {s: 2.0 * sizes[s] for s in over}


def test_mix_meets_targets(spark):
    rng = random.Random(5)
    texts = AWKWARD + [prose(rng, rng.randrange(1, 60)) for _ in range(900)]
    sources = ["b", "a", None, "é", "Z", ""]
    df = docs_frame(spark, texts, sources).union(docs_frame(spark, texts[:30], sources))
    got = mixing.mix(df).collect()
    assert len(got) == len(texts) + 30
    size, taken, largest, target = Counter(), Counter(), Counter(), {}
    for r in got:
        size[r["source"]] += r["size"]
        taken[r["source"]] += r["taken"]
        largest[r["source"]] = max(largest[r["source"]], r["size"])
        target[r["source"]] = r["target"]
        assert 0 <= r["taken"] <= 2 * r["size"] and r["source_size"] >= r["size"]
    want = brute_targets(size)
    for s in size:
        assert abs(target[s] - want[s]) < 1e-6 and abs(taken[s] - want[s]) <= 2 * largest[s]
    assert sorted(map(str, got)) == sorted(map(str, mixing.mix(df.repartition(7)).collect()))
    assert mixing.mix(df.limit(0)).count() == 0 and mixing.mix(docs_frame(spark, [None, ""])).agg(F.sum("taken")).first()[0] == 0


def test_larger_budgets_contain_smaller_ones(spark):
    rng = random.Random(6)
    df = docs_frame(spark, [prose(rng, 20) for _ in range(300)], ["a", "b"])
    less, more = ({r["doc_id"]: r["epochs"] for r in mixing.mix(df, (1, 1), share).collect()} for share in (0.4, 0.7))
    assert all(less[i] <= more[i] for i in less) and sum(less.values()) < sum(more.values())


# 4


def test_quality_separates_held_out_grades(spark):
    rng = random.Random(7)
    kinds = {0: "zz qq vv", 1: "mid tier soso", 2: "fine good best"}
    rows = [(g, " ".join(rng.choice((kinds[g] + " the of and to in").split()) for _ in range(30))) for g in [rng.randrange(3) for _ in range(600)]]
    model = quality.fit([t for _, t in rows[:400]], [g for g, _ in rows[:400]], 3)
    assert np.all(np.diff(model.cuts) > 0)
    df = docs_frame(spark, [t for _, t in rows[400:]] + AWKWARD)
    got = {r["doc_id"]: r for r in quality.quality_scores(df, model).collect()}
    assert len(got) == 200 + len(AWKWARD)
    right = sum(round(got[i]["expected_grade"]) == g for i, (g, _) in enumerate(rows[400:]))
    assert right >= 190 and all(1 >= r["tails"][0] >= r["tails"][1] >= 0 for r in got.values())
    assert quality.quality_scores(df.limit(0), quality.fit([], [], 3)).count() == 0


def test_ordinal_loss_and_gradients_by_hand():
    rng = np.random.default_rng(21)
    z, raw, y, weight = rng.normal(size=40), np.array([-0.7, 0.2, -0.4]), rng.integers(0, 4, 40), rng.uniform(0.5, 2, 40)
    cuts = [-0.7, -0.7 + np.exp(0.2), -0.7 + np.exp(0.2) + np.exp(-0.4)]
    assert np.allclose(quality.ordered_cuts(raw), cuts)

    def loss(z, raw):
        c, total = quality.ordered_cuts(raw), 0.0
        for zi, yi, wi in zip(z, y, weight):
            below = [0.0] + [1 / (1 + math.exp(-(k - zi))) for k in c] + [1.0]
            total -= wi * math.log(below[yi + 1] - below[yi])
        return total / len(y)

    got, gz, gr = quality.loss_and_gradients(z, raw, y, weight)
    assert math.isclose(got, loss(z, raw), rel_tol=1e-9)
    for i in range(len(z)):
        up, down = z.copy(), z.copy()
        up[i] += 1e-5
        down[i] -= 1e-5
        assert abs((loss(up, raw) - loss(down, raw)) / 2e-5 - gz[i]) < 1e-8
    for i in range(3):
        up, down = raw.copy(), raw.copy()
        up[i] += 1e-5
        down[i] -= 1e-5
        assert abs((loss(z, up) - loss(z, down)) / 2e-5 - gr[i]) < 1e-8


def slow_quality(model, text):
    """Tail probabilities from every word's three hashed parts, one by one."""
    words = (text or "").lower().split()
    seen, n = sorted(set(words)), max(1, len(words))
    bare = sum(1 for w in seen if not any(c.isalpha() for c in w))
    ceil8 = lambda v: math.ceil(8 * v)
    again = sum(1 for a, b in zip(words, words[1:]) if a == b)
    extra = [f"\0rep{ceil8(len(seen) / n)}", f"\0again{ceil8(again / n)}", f"\0bare{ceil8(bare / max(1, len(seen)))}", f"\0len{len(words).bit_length()}"]
    weigh = lambda w: sum(float(model.weights[zlib.crc32(f.encode()) % quality.DIM]) for f in ("w" + w, "p" + w[:4], "e" + w[-3:]))
    z = sum(map(weigh, seen)) / math.sqrt(max(1, len(seen))) + sum(map(weigh, extra))
    return [1 / (1 + math.exp(c - z)) for c in model.cuts]


def test_quality_query_equals_a_slow_version(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    model = quality.trained(docs, labels)
    got = {r["doc_id"]: r for r in QUERIES["op4_ordinal_quality"](spark, SF).collect()}
    rows = docs.select("doc_id", "text").collect()
    assert len(rows) == len(got)
    for r in rows:
        a, b = slow_quality(model, r["text"])
        g = got[r["doc_id"]]
        assert np.allclose([g["p_grade_1"], g["p_grade_2"], g["expected_grade"]], [a, b, a + b], atol=1e-5) and g["kept"] == (g["p_grade_1"] >= 0.5)


def test_grades_and_the_sample_they_give(spark, monkeypatch):
    labels = spark.createDataFrame([(i, q, t) for i, (q, t) in enumerate([(0, 0), (0, 1), (1, 1), (1, 0)] * 20)] + [(900, 1, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")
    graded = labels.withColumn("grade", quality.grade())
    assert {r["doc_id"]: r["grade"] for r in graded.where("doc_id < 4").collect()} == {0: 0, 1: 0, 2: 1, 3: 2}
    docs = docs_frame(spark, [f"text {i} " + "long " * 30_000 * (i == 3) for i in range(80)]).union(docs_frame(spark, [None]).withColumn("doc_id", F.lit(900).cast("long")))
    texts, grades = quality.sample(docs, graded, 3)
    assert sorted(grades) == [0] * 40 + [1] * 20 + [2] * 20 and any(len(t) > 100_000 for t in texts)
    monkeypatch.setattr(quality, "SAMPLE_PER_GRADE", 7)
    once, again = quality.sample(docs, graded, 3), quality.sample(docs.repartition(5), graded, 3)
    assert once == again and max(Counter(once[1]).values()) <= 7
    assert quality.sample(docs.limit(0), graded, 3) == ([], [])


# 5


def brute_removed(texts, length=100):
    seen, out = set(), []
    for t in texts:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for s in range(len(b) - length + 1):
            w = b[s : s + length]
            if w in seen:
                gone[s : s + length] = True
            seen.add(w)
        raw = np.frombuffer(b, np.uint8)
        out.append((len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(raw[~gone].tobytes()).hexdigest()))
    return out


def repeated_texts(rng):
    passages = [prose(rng, 60) for _ in range(4)]
    out = list(AWKWARD) + [passages[0]] * 3 + ["Is onhe. " * 60, "a" * 99, "a" * 100, "a" * 101, "é" * 120]
    for _ in range(40):
        out.append(" ".join([prose(rng, rng.randrange(30)), rng.choice(passages)[rng.randrange(40) :], prose(rng, rng.randrange(30))]))
    return out


@pytest.mark.parametrize("cap", [4096, 3])
def test_substring_dedup_equals_brute_force(spark, cap):
    texts = repeated_texts(random.Random(8))
    got = {r["doc_id"]: tuple(r)[1:] for r in substring_dedup.dedup_digest(docs_frame(spark, texts), group_cap=cap).collect()}
    assert [got[i] for i in range(len(texts))] == brute_removed(texts)


def test_substring_dedup_of_repeated_missing_and_no_rows(spark):
    t = prose(random.Random(9), 60)
    df = spark.createDataFrame([(2, t), (2, t), (None, t), (1, t)], "doc_id long, text string")
    got = sorted((r["doc_id"] or -1, r["n_removed"]) for r in substring_dedup.dedup_digest(df).collect())
    assert got == [(-1, 0), (1, 0), (2, len(t)), (2, len(t))]
    assert substring_dedup.dedup_digest(df.limit(0)).count() == 0


def test_repeated_rows_remove_nothing_of_their_own(spark):
    rng = random.Random(22)
    t, u = (bytes(rng.choices(range(97, 123), k=400)).decode() for _ in range(2))
    df = spark.createDataFrame([(1, t), (1, t), (2, u), (3, "x" + t)], "doc_id long, text string")
    got = sorted((r["doc_id"], r["n_removed"]) for r in substring_dedup.dedup_digest(df).collect())
    assert got == [(1, 0), (1, 0), (2, 0), (3, 400)]


def test_texts_that_share_an_id_follow_one_another(spark):
    rng = random.Random(23)
    texts = repeated_texts(rng)
    rows = [(i // 3, t) for i, t in enumerate(texts)] + [(2, texts[7]), (2, texts[7]), (None, texts[-1])]
    docs = sorted({(i, t) for i, t in rows if i is not None}, key=lambda r: (r[0], hashlib.md5((r[1] or "").encode()).hexdigest()))
    want = dict(zip(docs, brute_removed([t for _, t in docs])))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = Counter(tuple(r) for r in substring_dedup.dedup_digest(df).collect())
    expected = Counter((i, *want[i, t]) if i is not None else (None, len(t), 0, 0, hashlib.sha256(t.encode()).hexdigest()) for i, t in rows)
    # null and empty texts of one id have one digest and are one document
    assert got == expected
    cut = substring_dedup.dedup_texts(df)
    assert cut.count() == len(rows) and Counter(r["doc_id"] for r in cut.collect()) == Counter(i for i, _ in rows)


def test_dedup_texts_keeps_all_columns(spark):
    texts = repeated_texts(random.Random(10))
    out = substring_dedup.dedup_texts(docs_frame(spark, texts))
    assert out.columns == [f.split()[0] for f in DOCS.split(", ")]
    rows = {r["doc_id"]: r for r in out.collect()}
    for i, (n, gone, _, _) in enumerate(brute_removed(texts)):
        assert rows[i]["_spans"] == 3 and (texts[i] is None) == (rows[i]["text"] is None)
        if gone == 0 and texts[i] is not None:
            assert rows[i]["text"] == texts[i]


def test_suffix_array_is_the_sorted_order():
    rng = random.Random(11)
    for _ in range(3000):
        s = [rng.randrange(rng.randrange(1, 5)) for _ in range(rng.randrange(16))]
        order = suffix_array.suffix_array(s)
        assert order == sorted(range(len(s)), key=lambda i: s[i:])
        for k, h in enumerate(suffix_array.common_prefixes(s, order)):
            if k:
                a, b = s[order[k - 1] :], s[order[k] :]
                assert a[:h] == b[:h] and (len(a) == h or len(b) == h or a[h] != b[h])


# 6


def test_best_fit_packing(spark):
    rng = random.Random(12)
    texts = AWKWARD + [prose(rng, rng.randrange(1, 1500)) for _ in range(60)] + ["tie tie tie"] * 30
    df = docs_frame(spark, texts)
    encode, cap = tokens.encoder(tokens.default_vocabulary()), 512
    got = packing.pack(packing.token_pieces(df, cap), cap).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, t in enumerate(texts):
        ids = np.append(encode(t or ""), np.uint32(0)).astype("<u4")
        pieces = sorted(by_doc[i], key=lambda r: r["piece"])
        assert [(r["start"], r["length"]) for r in pieces] == tokens.split_points(len(ids), cap)
        assert all(zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"] for r in pieces)
    for spans in by_seq.values():
        at = 0
        for o, n in sorted(spans):
            assert o == at
            at += n
        assert at <= cap
    assert len(by_seq) == len(binary_output.best_fit_decreasing([r["length"] for r in got], cap))
    assert packing.pack(packing.token_pieces(df.limit(0), cap), cap).count() == 0


def test_supersteps_are_best_fit_decreasing():
    rng = random.Random(13)
    for _ in range(300):
        cap = rng.randrange(5, 60)
        sizes = [rng.randrange(1, cap + 1) for _ in range(rng.randrange(80))]
        placed = defaultdict(dict)
        for length, lo, hi, first, each, off in packing.supersteps(Counter(sizes), cap):
            for r in range(lo, hi):
                placed[first + (r - lo) // each][off + (r - lo) % each * length] = length
        for seq in placed.values():
            at = 0
            for o in sorted(seq):
                assert o == at
                at += seq[o]
            assert at <= cap
        assert sum(map(len, placed.values())) == len(sizes) and len(placed) == len(binary_output.best_fit_decreasing(sizes, cap))


# 7


def test_hamming_search_is_exact(spark):
    rng = np.random.default_rng(14)
    centres = rng.integers(-(2**63), 2**63 - 1, 12, dtype=np.int64)
    codes = np.concatenate([centres[rng.integers(0, 12, 500)] ^ (np.int64(1) << rng.integers(0, 63, 500)), np.full(400, centres[0]), rng.integers(-(2**63), 2**63 - 1, 300, dtype=np.int64)])
    rows = spark.createDataFrame([(i, int(c)) for i, c in enumerate(codes)] + [(9999, None), (None, 5)], "id long, code long")
    got = defaultdict(list)
    for r in hamming.top_k(rows, rows.where("id % 50 = 0"), 7).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["distance"], r["neighbour_id"]))
    u = codes.view(np.uint64)
    for q in range(0, len(codes), 50):
        d = np.bitwise_count(u ^ u[q])
        assert got[q] == sorted((int(x), i) for i, x in enumerate(d) if i != q)[:7]
    assert hamming.top_k(rows.limit(0), rows.limit(0)).count() == 0 and hamming.top_k(rows.where("id < 3"), rows.where("id = 0"), 7).count() == 2


def test_repeated_rows_take_no_place_of_other_ids_of_a_hot_code(spark):
    rows = spark.createDataFrame([(i, 77) for i in range(40) for _ in range(3)] + [(100 + i, 77 ^ (1 << i)) for i in range(5)], "id long, code long")
    got = defaultdict(list)
    for r in hamming.top_k(rows, rows.where("id in (0, 20, 100)"), 10).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["distance"], r["neighbour_id"]))
    assert got == {0: [(0, i) for i in range(1, 11)], 20: [(0, i) for i in range(10)], 100: [(1, i) for i in range(10)]}


def test_thirty_repeated_rows_hide_no_neighbour(spark):
    rows = spark.createDataFrame([(1, 0)] * 30 + [(2, 0), (3, 0), (4, 0), (5, 1), (6, 7)], "id long, code long")
    got = [tuple(r)[2:] for r in hamming.top_k(rows, rows.where("id = 5"), 10).orderBy("rank").collect()]
    assert got == [(1, 1), (2, 1), (3, 1), (4, 1), (6, 2)]


@pytest.mark.parametrize("codes, queries", [(50, 10**6), (50, 7)])
def test_shards_and_query_blocks_give_one_answer(spark, monkeypatch, codes, queries):
    rng = np.random.default_rng(24)
    rows = spark.createDataFrame([(i, int(c)) for i, c in enumerate(rng.integers(-(2**63), 2**63 - 1, 600, dtype=np.int64))], "id long, code long")
    whole = hamming.top_k(rows, rows.where("id % 20 = 0"), 5).orderBy("query_id", "rank").collect()
    monkeypatch.setattr(hamming, "CELL_CODES", codes)
    monkeypatch.setattr(hamming, "CELL_QUERIES", queries)
    assert hamming.top_k(rows, rows.where("id % 20 = 0"), 5).orderBy("query_id", "rank").collect() == whole


def test_search_stops_before_it_has_seen_everything():
    rng = np.random.default_rng(15)
    codes = np.unique(rng.integers(0, 2**63, 20_000, dtype=np.int64)).view(np.uint64)
    near = codes[0] ^ np.uint64(5)
    mi = hamming.MultiIndex(np.append(codes, near), np.ones(len(codes) + 1, int))
    assert set(mi.search(int(codes[0]), 2).tolist()) == {0, len(codes)}


# 8


def test_relative_and_later_targets_are_edges(spark):
    html = ['<link rel="canonical" href="/de/x"><link rel="canonical" href="http://b.io/2">', '<meta http-equiv="refresh" content="0; url=//example.com/de/y?q#f">', '<link rel=canonical href="../up/./z"><meta http-equiv=refresh content="0;url=?p=2">', '<link rel="canonical" href="#top"><link rel="canonical" href="mailto:a@b">', "<link rel=canonical href='plain'>"]
    urls = ["http://example.com/en/a", "https://calm.io/one", "http://c.io/a/b/c?k", "http://d.io/", "http://e.io"]
    pages = spark.createDataFrame([(i, u, h) for i, (u, h) in enumerate(zip(urls, html))], "page_id long, url string, html string")
    edges = url_filter.declared_edges(pages)
    want = {(urls[0], "http://example.com/de/x"), (urls[0], "http://b.io/2"), (urls[1], "https://example.com/de/y?q#f"), (urls[2], "http://c.io/a/up/z"), (urls[2], "http://c.io/a/b/c?p=2"), (urls[4], "http://e.io/plain")}
    assert {tuple(r) for r in edges.collect()} == want
    assert {r["page_id"]: r["verdict"] for r in url_filter.url_verdicts(pages, edges).collect()} == {0: "block", 1: "block", 2: "allow", 3: "allow", 4: "allow"}


def test_url_rules_aliases_and_malformed_urls(spark):
    urls = ["http://a.net/x", "https://www.example.net/en/1?q", "http://EXAMPLE.net/en", "http://example.com/de/1", "http://x.org/fr/", "http://x.org/de/", None, "no scheme", "http://notnet/", "ftp://net", "http://sub.example.com/de/#f", "http://plain.io/p", "http://mirror.io/p", "http://calm.io/"]
    pages = spark.createDataFrame([(i, u, 1, "r") for i, u in enumerate(urls)], "page_id long, url string, component int, rule string")
    edges = spark.createDataFrame([("http://mirror.io/p", "http://plain.io/p"), ("http://plain.io/p", "http://example.com/de/1"), ("https://www.example.net/en/1?q", "http://example.com/de/1"), ("http://calm.io/", "http://x.org/fr/")], "u string, v string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.url_verdicts(pages, edges).collect()}
    assert got[0] == ("a.net", "/x", "net/", "block") and got[1] == ("www.example.net", "/en/1", "example.net/en/", "allow")
    assert got[2] == ("example.net", "/en", "net/", "block") and got[3][2:] == ("example.com/de/", "block") and got[4][2:] == ("org/fr/", "allow")
    assert got[5] == ("x.org", "/de/", None, "allow") and got[6] == ("", "", None, "allow") == got[7] and got[8][2:] == (None, "allow")
    assert got[9] == ("net", "", None, "allow") and got[10] == ("sub.example.com", "/de/", "example.com/de/", "block")
    assert got[11][3] == got[12][3] == "block" and got[13][3] == "allow"
    assert url_filter.url_verdicts(pages.limit(0), edges.limit(0)).count() == 0


def test_aliases_of_many_pages_equal_a_sequential_union(spark):
    """50,000 pages with a hot target, long redirect chains and canonical links, through the HTML."""
    rng, n = random.Random(25), 50_000
    hosts = ["a.net", "b.org", "example.com", "c.io", "www.example.net", "d.de"]
    urls = [f"http://{rng.choice(hosts)}/{rng.choice(['en', 'de', 'fr'])}/{i}" for i in range(n)]
    links = {}
    for i in range(n):
        kind = rng.random()
        if kind < 0.3:
            links[i] = (urls[7], "canonical")  # a third of all pages name one page
        elif kind < 0.5 and i + 1 < n:
            links[i] = (urls[i + 1], "refresh")
        elif kind < 0.55:
            links[i] = (f"/en/moved/{i % 50}", "canonical")
    tag = {"canonical": '<link rel="canonical" href="%s">', "refresh": '<meta http-equiv="refresh" content="0; url=%s">'}
    pages = spark.createDataFrame([(i, u, "<html>" + (tag[links[i][1]] % links[i][0] if i in links else "")) for i, u in enumerate(urls)], "page_id long, url string, html string")
    up = {}

    def find(x):
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for i, (target, _) in links.items():
        target = target if "://" in target else "/".join(urls[i].split("/")[:3]) + target
        up[find(urls[i])] = find(target)

    def rule(url):
        host, path = url.split("/")[2], "/" + "/".join(url.split("/")[3:])
        fits = [(len(h + p), k) for k, h, p in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        return max(fits)[1] if fits else None

    blocked = {find(u) for u in list(up) if rule(u) == "block"}
    edges = url_filter.declared_edges(pages)
    assert edges.count() == len(links)
    got = {r["page_id"]: r["verdict"] for r in url_filter.url_verdicts(pages, edges).select("page_id", "verdict").collect()}
    assert got == {i: rule(u) or ("block" if u in up and find(u) in blocked else "allow") for i, u in enumerate(urls)}


def test_links_are_read_from_html(spark):
    html = ['<LINK href="http://a/1" rel="canonical">', "<link rel=canonical href='http://a/2'>", '<meta http-equiv="refresh" content="0; url=http://a/3">', "<p>none</p>", None, '<link rel="canonical" href="/relative">']
    df = spark.createDataFrame([(f"http://p/{i}", h) for i, h in enumerate(html)], "url string, html string")
    assert sorted(tuple(r) for r in url_filter.link_edges(df).collect()) == [(f"http://p/{i}", f"http://a/{i + 1}") for i in range(3)]


# 9


def test_matroska_round_trip(spark):
    texts = AWKWARD + ["q" * n for n in (575, 576, 577, 576 * 8, 576 * 33 + 1)]
    media = matroska.media_column(docs_frame(spark, texts)).persist()
    got = {r["doc_id"]: r for r in matroska.media_digest(media).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        padded = raw + b"\xff" * (-len(raw) % 576 or (576 if not raw else 0))
        r = got[i]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-32:])) and r["error"] is None
    packets = matroska.packet_table(media).where("doc_id = 13").orderBy("packet").collect()
    assert [p["timestamp_ms"] for p in packets] == [72 * k for k in range(len(packets))] and {p["lacing"] for p in packets} == {0, 1, 2, 3} or len(packets) == 34
    assert matroska.media_digest(media.limit(0)).count() == 0


@pytest.mark.parametrize("mode", [matroska.XIPH, matroska.EBML_LACE])
def test_lacing_of_unequal_frames(mode):
    rng = random.Random(16)
    frames = [bytes([k]) * rng.choice([0, 1, 127, 128, 254, 255, 256, 600, 20_000]) for k in range(40)]
    body = matroska.vint(1) + struct.pack(">hB", 0, mode << 1) + matroska.lace(frames, mode)
    assert [body[s : s + n] for s, n in matroska.unlace(body, 0, len(body))[3]] == frames


def test_unknown_sizes_cues_and_damage(spark):
    block = matroska.element(matroska.SIMPLE_BLOCK, matroska.vint(1) + struct.pack(">hB", 5, 0) + b"abc")
    cluster = matroska.CLUSTER.to_bytes(4, "big") + b"\x01" + b"\xff" * 7 + matroska.uint(matroska.CLUSTER_TIME, 10) + block
    data = matroska.SEGMENT.to_bytes(4, "big") + b"\xff" + cluster + cluster
    packets = matroska.demux(data)["packets"]
    assert [(p[1], p[2], data[p[4] : p[4] + p[5]]) for p in packets] == [(15, 0, b"abc"), (15, 1, b"abc")]
    whole = matroska.mux(b"z" * 576 * 70)
    got = matroska.demux(whole)
    assert len(got["cues"]) == 3 and all(int.from_bytes(whole[at : at + 4], "big") == matroska.CLUSTER for _, _, at in got["cues"])
    null = spark.createDataFrame([(7, 3, None)], "doc_id long, n_bytes long, media binary")
    assert tuple(matroska.media_digest(null).first()) == (7, 3, *[None] * 7) and matroska.packet_table(null).count() == 0
    df = spark.createDataFrame([(1, 3, bytearray(whole[:-9])), (2, 3, bytearray(b"\x00"))], "doc_id long, n_bytes long, media binary")
    assert all(r["error"] for r in matroska.media_digest(df).collect()) and matroska.packet_table(df).where("error is not null").count() == 2


# 10


def test_forward_backward_equals_enumeration():
    rng = np.random.default_rng(17)
    s, pair, start = rng.normal(size=(3, 5)), rng.normal(size=(2, 2)), 0.4
    lengths = [5, 3, 1]
    mask = np.arange(5)[None, :] < np.array(lengths)[:, None]
    post, moves, logz = toxicity.forward_backward(s, mask, pair, start)
    quick = toxicity.quick_marginals(np.where(mask, s, 0.0), mask, pair, start)
    want_moves = np.zeros((2, 2))
    for r, n in enumerate(lengths):
        weights, marg, total = {}, np.zeros(n), 0.0
        for bits in range(1 << n):
            y = [bits >> i & 1 for i in range(n)]
            w = np.exp(start * y[0] + sum(s[r, i] for i in range(n) if y[i]) + sum(pair[a, b] for a, b in zip(y, y[1:])))
            weights[bits] = w
            total += w
            marg += w * np.array(y)
        for bits, w in weights.items():
            y = [bits >> i & 1 for i in range(n)]
            for a, b in zip(y, y[1:]):
                want_moves[a, b] += w / total
        fast, fast_moves, fast_logz = toxicity.expectations(s, mask, pair, start)
        assert np.allclose(fast, post) and np.allclose(fast_moves, moves) and np.allclose(fast_logz, logz)
        assert np.allclose(post[r, :n], marg / total) and np.allclose(quick[r, :n], marg / total) and np.isclose(logz[r], np.log(total))
    assert np.allclose(moves, want_moves)


@pytest.mark.parametrize("pair", [[[1.0, -1.0], [0.0, 0.5]], [[4.0, -6.0], [-5.0, 6.0]], [[0.0, 9.0], [9.0, 0.0]]])
def test_long_texts_are_one_chain(pair):
    rng, pair = np.random.default_rng(18), np.array(pair)
    lengths = [3000, 256, 257, 1, 0, 512, 700, 40]
    scores = [rng.normal(-1, 3, n) for n in lengths]
    got = toxicity.marginals(scores, pair, -0.5)
    for s, m in zip(scores, got):
        if len(s):
            whole, _, _ = toxicity.forward_backward(s[None, :], np.ones((1, len(s)), bool), pair, -0.5)
            assert np.abs(whole[0] - m).max() < 1e-9
        else:
            assert len(m) == 0


def test_offsets_are_those_of_the_text(spark):
    bad = [("fine words and a vilething here", 1), ("fine words and nothing else here", 0)]
    rng = random.Random(26)
    texts = [(" ".join([prose(rng, 20), w, prose(rng, 20)]), y) for w, y in bad * 60]
    field = toxicity.fit([t for t, _ in texts], [y for _, y in texts])
    odd = ["\u0130" * 10 + " " + prose(rng, 10) + " VileThing " + "\u0130 x", "vilething", "\U0001f600 \u1e9e vilething"]
    rows = {r["doc_id"]: r for r in toxicity.toxicity_scores(docs_frame(spark, odd), field).collect()}
    for i, t in enumerate(odd):
        assert [t[s["start"] : s["end"]].lower() for s in rows[i]["spans"]] == ["vilething"]


def test_toxicity_is_fitted_on_every_window(monkeypatch):
    texts = [" ".join(f"w{i}x{k}" for k in range(300)) for i in range(40)] + ["vile " * 9] * 4
    seen, plain = [], toxicity.expectations
    monkeypatch.setattr(toxicity, "expectations", lambda s, mask, *a: seen.append(int(mask.sum())) or plain(s, mask, *a))
    toxicity.fit(texts, [0] * 40 + [1] * 4)
    assert set(seen) == {40 * 300 + 4 * 9}


def test_a_shared_common_triple_makes_no_copy():
    words = [["a", "a", "a", *(f"word{k * 7 + i * 1000}" for k in range(60))] for i in range(20)]
    assert toxicity.distinct(words + words[:3]) == list(range(20))


def test_toxicity_on_held_out_texts(spark):
    rng = random.Random(19)
    rows = []
    for _ in range(900):
        w = prose(rng, rng.randrange(20, 400)).split()
        y = rng.random() < 0.3
        if y:
            for _ in range(3):
                w.insert(rng.randrange(len(w)), rng.choice(["badword", "vilething", "grub" + str(rng.randrange(1000))]))
        rows.append((" ".join(w), int(y)))
    field = toxicity.fit([t for t, _ in rows[:600]], [y for _, y in rows[:600]])
    texts = [t for t, _ in rows[600:]] + AWKWARD
    got = {r["doc_id"]: r for r in toxicity.toxicity_scores(docs_frame(spark, texts), field).collect()}
    assert len(got) == len(texts) and all(0 <= r["score"] <= 1 for r in got.values())
    wrong = sum((got[i]["score"] >= 0.7) != bool(y) for i, (_, y) in enumerate(rows[600:]))
    assert wrong <= 6
    for i, (t, y) in enumerate(rows[600:]):
        for s in got[i]["spans"]:
            assert not y or re.search("badword|vilething|grub", t[s["start"] : s["end"]])
    assert all(got[300 + i]["score"] < 0.7 for i in range(len(AWKWARD)))
    assert toxicity.toxicity_scores(docs_frame(spark, texts).limit(0), field).count() == 0


def test_labels_of_held_out_rows_are_never_used(spark):
    docs = docs_frame(spark, ["t %d" % i for i in range(200)])
    flip = F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, 1 - F.col("toxic")).otherwise(F.col("toxic"))
    labels = docs.select("doc_id", (F.col("doc_id") % 2).cast("int").alias("toxic"))
    assert toxicity.sample(docs, labels) == toxicity.sample(docs, labels.withColumn("toxic", flip))


def test_shingle_sets_match_words():
    p = shingles.Powers()
    assert shingles.shingle_set("A b  C\td\ne", p).tolist() == shingles.shingle_set("a B c D e", p).tolist()
    assert len(shingles.shingle_set("É a b c d", p)) == 1 and shingles.shingle_set("É a b c d", p).tolist() != shingles.shingle_set("é a b c d", p).tolist()
    assert len(shingles.shingle_set(None, p)) == len(shingles.shingle_set(" \n", p)) == 0
