"""Toxic spans by a two-tag linear-chain conditional random field, and document scores from its marginals.

Ratings exist for documents only, so token tags for training come from rated documents: a word or word beginning that keeps to toxic
ones (by a likelihood-ratio test) tags its tokens. The field then learns weights of hashed word features and tag transitions; forward-
backward marginals give spans with offsets, and their maximum and sum give the document's probability.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slices, table

WORD = re.compile(r"\w+")
#: Training sample: rated documents at most for each rating. Their whole texts are used, in training and in scoring.
SAMPLE_TOXIC, SAMPLE_CLEAN = 1500, 3000
DIM = 1 << 17
#: Likelihood-ratio bound and share of toxic documents from which a feature tags tokens.
MIN_G, MIN_PURITY = 30.0, 0.97
#: Passes over the sample at most, the share of the loss that a pass must still gain, windows a step, the optimiser's step and penalty.
PASSES, GAIN, LOT, STEP, L2 = 20, 0.1, 128, 0.1, 1.0
#: Tokens of a training window and of a block of the scan over long texts.
CORE = 256
THRESHOLD = 0.7
CACHE = 400_000


def lowered(text: str | None) -> str:
    """Lower case, character by character, so that offsets stay those of the text (U+0130 alone would become two)."""
    return (text or "").replace("\u0130", "I").lower()


def features(word: str) -> list[str]:
    return ["w" + word, "3" + word[:3], "4" + word[:4], "5" + word[:5], "e" + word[-3:]]


def slots(word: str) -> list[int]:
    return [zlib.crc32(f.encode("utf-8", "surrogatepass")) % DIM for f in features(word)]


@dataclass
class Field:
    weights: np.ndarray  # log-potential of the toxic tag by feature slot
    pair: np.ndarray  # 2 x 2 transition log-potentials, [from, to]
    start: float  # log-potential of a toxic first token
    link: tuple[float, float, float]  # intercept, weights of the largest marginal's log-odds and of log1p(sum)


def forward_backward(s: np.ndarray, mask: np.ndarray, pair: np.ndarray, start: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Marginals of the toxic tag, expected transitions (2 x 2) and log-partition per row, for rows of emission scores s."""
    n, length = s.shape
    a, e = np.exp(pair), np.exp(np.clip(s, -30, 30))
    alpha, beta, logz = np.empty((length, n, 2)), np.ones((length, n, 2)), np.zeros(n)
    for t in range(length):
        if t == 0:
            cur = np.stack([np.ones(n), np.full(n, math.exp(start))], 1)
        else:
            cur = alpha[t - 1] @ a
        cur[:, 1] *= e[:, t]
        z = cur.sum(1)
        cur /= z[:, None]
        live = mask[:, t]
        logz += np.where(live, np.log(z), 0)
        alpha[t] = cur if live.all() or t == 0 else np.where(live[:, None], cur, alpha[t - 1])
    for t in range(length - 2, -1, -1):
        nxt = beta[t + 1].copy()
        nxt[:, 1] *= e[:, t + 1]
        cur = nxt @ a.T
        cur /= cur.sum(1)[:, None]
        live = mask[:, t + 1]
        beta[t] = cur if live.all() else np.where(live[:, None], cur, 1.0)
    post = alpha * beta
    post /= post.sum(2, keepdims=True)
    joint = alpha[:-1, :, :, None] * a[None, None] * (np.stack([np.ones_like(e), e], 2).transpose(1, 0, 2)[1:] * beta[1:])[:, :, None, :]
    joint /= joint.sum((2, 3), keepdims=True)
    moves = (joint * mask.T[1:, :, None, None]).sum((0, 1)) if length > 1 else np.zeros((2, 2))
    return np.where(mask, post[:, :, 1].T, 0.0), moves, logz


def block_products(e: np.ndarray, mask: np.ndarray, pair: np.ndarray) -> np.ndarray:
    """For every row of emission factors, the 2 x 2 product over its tokens of (transition into the token, its emission), up to a factor."""
    a = np.exp(pair)
    n, length = e.shape
    p = np.tile(np.eye(2), (n, 1, 1))
    for t in range(length):
        nxt = p @ a
        nxt[:, :, 1] *= e[:, t, None]
        nxt /= nxt.max(axis=(1, 2), keepdims=True)
        live = mask[:, t]
        p = nxt if live.all() else np.where(live[:, None, None], nxt, p)
    return p


def marginals(scores: list[np.ndarray], pair: np.ndarray, start: float) -> list[np.ndarray]:
    """Toxic-tag marginals of every token, each text as one chain whatever its length.

    Texts are cut into blocks of CORE tokens, and lots of blocks go through vector operations together. The chain crosses block
    borders exactly: a scan over the blocks' transition products gives the odds of the tag before every block and what all later
    blocks say about its last tag.
    """
    out = [np.zeros(len(s)) for s in scores]
    blocks = [(d, c, min(c + CORE, len(s))) for d, s in enumerate(scores) for c in range(0, len(s), CORE)]
    at = {(d, c): k for k, (d, c, _) in enumerate(blocks)}
    # the odds of a toxic tag before the block (None: the text starts here) and the tag's likelihood ratio after it
    before, after = np.full(len(blocks), np.nan), np.ones(len(blocks))

    def lots(which):
        which = sorted(which, key=lambda k: blocks[k][2] - blocks[k][1])
        for i in range(0, len(which), 1024):
            part = which[i : i + 1024]
            width = max(blocks[k][2] - blocks[k][1] for k in part)
            s, mask = np.zeros((len(part), width)), np.zeros((len(part), width), bool)
            for r, k in enumerate(part):
                d, lo, hi = blocks[k]
                s[r, : hi - lo], mask[r, : hi - lo] = scores[d][lo:hi], True
            yield part, s, mask

    long = [d for d, s in enumerate(scores) if len(s) > CORE]
    if long:
        product = np.empty((len(blocks), 2, 2))
        rest = [at[d, c] for d in long for c in range(CORE, len(scores[d]), CORE)]
        for part, s, mask in lots(rest):
            product[part] = block_products(np.exp(np.clip(s, -30, 30)), mask, pair)
        first = [at[d, 0] for d in long]
        for part, s, mask in lots(first):
            before[[k + 1 for k in part]] = odds_forward(np.ascontiguousarray(np.exp(np.clip(s, -30, 30)).T), pair, np.full(len(part), math.exp(start)), True)[-1]
        for d in long:
            ks = [at[d, c] for c in range(0, len(scores[d]), CORE)]
            for k in ks[1:-1]:  # row vector (1, odds) times the block's product
                p, o = product[k], before[k]
                before[k + 1] = (p[0, 1] + o * p[1, 1]) / (p[0, 0] + o * p[1, 0])
            for k in reversed(ks[1:]):  # the block's product times column vector (1, ratio)
                p, r = product[k], after[k]
                after[k - 1] = (p[1, 0] + p[1, 1] * r) / (p[0, 0] + p[0, 1] * r)
    for part, s, mask in lots(range(len(blocks))):
        m = quick_marginals(s, mask, pair, start, before[part], after[part])
        for r, k in enumerate(part):
            d, lo, hi = blocks[k]
            out[d][lo:hi] = m[r, : hi - lo]
    return out


def odds_forward(e: np.ndarray, pair: np.ndarray, cur: np.ndarray, at_start: bool | np.ndarray) -> np.ndarray:
    """Odds of the toxic tag given the tokens so far, (tokens, rows); cur: odds before a row's first token, or its prior at a start."""
    (oo, ot), (to, tt) = np.exp(pair)
    f = np.empty_like(e)
    cur = np.where(at_start, cur, (ot + cur * tt) / (oo + cur * to)) * e[0]
    f[0] = cur
    for t in range(1, len(e)):
        cur = (ot + cur * tt) / (oo + cur * to) * e[t]
        f[t] = cur
    return f


def quick_marginals(s: np.ndarray, mask: np.ndarray, pair: np.ndarray, start: float, before: np.ndarray | None = None, after: np.ndarray | None = None) -> np.ndarray:
    """The marginals of forward_backward() alone, in odds form, which needs a few vector operations a token. before: odds of the tag
    before each row (nan where a text starts); after: what later tokens say about a row's last tag, as a likelihood ratio."""
    (oo, ot), (to, tt) = np.exp(pair)
    n, length = s.shape
    e = np.ascontiguousarray(np.exp(np.clip(s, -30, 30)).T)
    starts = np.ones(n, bool) if before is None else np.isnan(before)
    f = odds_forward(e, pair, np.full(n, math.exp(start)) if before is None else np.where(starts, math.exp(start), before), starts)
    end = np.ones(n) if after is None else after
    back, live = end, mask.T
    f[length - 1] *= back
    for t in range(length - 2, -1, -1):
        x = back * e[t + 1]
        back = np.where(live[t + 1], (to + tt * x) / (oo + ot * x), end)
        f[t] *= back
    return (f / (1 + f)).T


def expectations(s: np.ndarray, mask: np.ndarray, pair: np.ndarray, start: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What forward_backward() gives, from odds: only the two recursions run token by token, all else over whole arrays."""
    (oo, ot), (to, tt) = np.exp(pair)
    n, length = s.shape
    e, live = np.ascontiguousarray(np.exp(np.clip(s, -30, 30)).T), np.ascontiguousarray(mask.T)
    f = odds_forward(e, pair, np.full(n, math.exp(start)), True)
    back = np.ones_like(e)
    for t in range(length - 2, -1, -1):
        x = back[t + 1] * e[t + 1]
        back[t] = np.where(live[t + 1], (to + tt * x) / (oo + ot * x), 1.0)
    both = f * back
    g, x = f[:-1], e[1:] * back[1:]
    a, b, c = ot * x, to * g, tt * g * x
    share = live[1:] / (oo + a + b + c)
    moves = np.array([[oo * share.sum(), (a * share).sum()], [(b * share).sum(), (c * share).sum()]])
    steps = np.log((oo + g * to) + (ot + g * tt) * e[1:]) - np.log1p(g)
    logz = np.where(live[0], np.log1p(math.exp(start) * e[0]), 0.0) + np.where(live[1:], steps, 0.0).sum(0)
    return np.where(mask, (both / (1 + both)).T, 0.0), moves, logz


def mixed(h: np.ndarray) -> np.ndarray:
    """Another order of 32-bit hashes, by multiplications and shifts that lose nothing."""
    h = (h ^ (h >> 16)) * np.uint32(0x85EBCA6B)
    h = (h ^ (h >> 13)) * np.uint32(0xC2B2AE35)
    return h ^ (h >> 16)


def distinct(words: list[list[str]]) -> list[int]:
    """Documents without those that share one of two least hashes of word triples with an earlier one: copies must not count as evidence."""
    seen, out = set(), []
    for i, ws in enumerate(words):
        triples = [" ".join(ws[k : k + 3]).encode("utf-8", "surrogatepass") for k in range(max(1, len(ws) - 2))]
        h = np.fromiter(map(zlib.crc32, triples), np.uint32, len(triples))
        keys = {(0, int(h.min())), (1, int(mixed(h).min()))}
        if not keys & seen:
            out.append(i)
        seen |= keys
    return out


def weak_tags(words: list[list[str]], toxic: list[int]) -> set[str]:
    """Features whose documents are toxic ones, by Dunning's likelihood ratio against independence."""
    own = distinct(words)
    words, toxic = [words[i] for i in own], [toxic[i] for i in own]
    n, n1 = len(words), sum(toxic)
    of = lambda ws: {f for w in set(ws) if len(w) > 2 for f in features(w)[:4]}
    bad = Counter(f for ws, y in zip(words, toxic) if y for f in of(ws))
    bad = {f: k for f, k in bad.items() if k > 2}  # fewer can never reach the bound; this keeps the tables small
    with_ = Counter(f for ws in words for f in of(ws) if f in bad)
    found, base = set(), n1 / max(n, 1)
    for f, k in bad.items():
        m = with_[f]
        if k / m < MIN_PURITY or (f[0] in "345" and len(f) - 1 < int(f[0])):
            continue
        inside = k * math.log(k / (m * base)) + (m - k) * math.log(max(m - k, 1e-9) / (m * (1 - base)) if m > k else 1)
        if 2 * inside >= MIN_G:
            found.add(f)
    return found


def fit(texts: list[str], toxic: list[int]) -> Field:
    """Maximum-likelihood weights with an L2 penalty by Adam over all windows of the texts, pass after pass until one gains little, in a
    fixed order: equal inputs give equal fields."""
    one: dict[str, str] = {}  # one string a word
    words = [[one.setdefault(w, w) for w in WORD.findall(lowered(t))] for t in texts]
    none = Field(np.zeros(DIM, np.float32), np.zeros((2, 2)), 0.0, (-6.0, 0.0, 0.0))
    if not sum(toxic) or sum(toxic) == len(toxic):
        return none
    marks = weak_tags(words, toxic)
    vocab = {w: i for i, w in enumerate(sorted({w for ws in words for w in ws}))}
    of = np.array([slots(w) for w in vocab] or [[0] * 5])
    tag = np.array([float(any(f in marks for f in features(w)[:4])) for w in vocab] or [0.0])
    ids = [np.array([vocab[w] for w in ws], dtype=np.int32) for ws in words]
    del words  # the words' places in the vocabulary are enough from here on
    seq = [(d, c) for d, part in enumerate(ids) for c in range(0, len(part), CORE)]
    w, pair, start = np.zeros(DIM), np.array([[1.0, -1.0], [0.0, 0.0]]), -2.0
    params = [w, pair, np.array([start])]
    m1, m2 = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    seq.sort(key=lambda w: (min(CORE, len(ids[w[0]]) - w[1]), w))
    batches = []
    for k in range(0, len(seq), LOT):
        lot = [(ids[d][c : c + CORE], toxic[d]) for d, c in seq[k : k + LOT]]
        size = np.array([len(part) for part, _ in lot])
        x = np.zeros((len(lot), size.max()), np.int32)
        for r, (part, _) in enumerate(lot):
            x[r, : len(part)] = part
        mask = np.arange(x.shape[1]) < size[:, None]
        g = mask & (tag[x] > 0) & (np.array([y for _, y in lot])[:, None] > 0)
        real = np.array([[((g[:, :-1] == a) & (g[:, 1:] == b) & mask[:, 1:]).sum() for b in (False, True)] for a in (False, True)], float)
        batches.append((x, mask, g, real))
    step, turns, before = 0, np.random.default_rng(1), math.inf
    for _ in range(PASSES):
        loss = 0.0
        for x, mask, g, real in (batches[k] for k in turns.permutation(len(batches))):
            step += 1
            word_score = params[0][of].sum(1)
            s = np.where(mask, word_score[x], 0.0)
            post, moves, logz = expectations(s, mask, params[1], float(params[2][0]))
            loss += float(logz.sum() - (g * s).sum() - (real * params[1]).sum() - params[2][0] * g[:, 0].sum())
            scale = 1.0 / mask.sum()
            diff = np.where(mask, post - g, 0.0)
            per_word = np.bincount(x[mask], weights=diff[mask], minlength=len(of)) * scale
            gw = np.bincount(of.ravel(), weights=np.repeat(per_word, of.shape[1]), minlength=DIM)
            grads = [gw + L2 * params[0] * scale, (moves - real) * scale, np.array([(post[:, 0] - g[:, 0]).sum() * scale])]
            for p, gr, a1, a2 in zip(params, grads, m1, m2):
                a1 += 0.1 * (gr - a1)
                a2 += 0.01 * (gr * gr - a2)
                p -= STEP * (a1 / (1 - 0.9**step)) / (np.sqrt(a2 / (1 - 0.99**step)) + 1e-8)
        if loss > (1 - GAIN) * before:
            break
        before = loss
    field = Field(params[0].astype(np.float32), params[1], float(params[2][0]), none.link)
    word_score = field.weights[of].sum(1)
    lots = [ids[k : k + 256] for k in range(0, len(ids), 256)]
    stats = np.array([summary(m) for lot in lots for m in marginals([word_score[part].astype(float) for part in lot], field.pair, field.start)]).reshape(-1, 2)
    field.link = logistic(stats, np.array(toxic, float))
    return field


def summary(m: np.ndarray) -> tuple[float, float]:
    if not len(m):
        return math.log(1e-6), 0.0
    top = min(max(float(m.max()), 1e-6), 1 - 1e-6)
    return math.log(top / (1 - top)), math.log1p(float(m[m > 0.2].sum()))


def logistic(x: np.ndarray, y: np.ndarray, rounds: int = 25) -> tuple[float, float, float]:
    """Ridge logistic regression by Newton steps."""
    z, b = np.column_stack([np.ones(len(x)), x]), np.zeros(3)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ b, -30, 30)))
        h = (z * (p * (1 - p))[:, None]).T @ z + np.diag([1e-3, 1.0, 1.0])
        b = b + np.linalg.solve(h, z.T @ (y - p) - np.array([0, b[1], b[2]]))
    return tuple(b.tolist())


def score_words(field: Field, words: list[str], cache: dict[str, float]) -> np.ndarray:
    out = np.empty(len(words))
    get, w = cache.get, field.weights
    for i, word in enumerate(words):
        s = get(word)
        if s is None:
            if len(cache) >= CACHE:
                cache.clear()
            s = cache[word] = float(w[slots(word)].sum())
        out[i] = s
    return out


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def sample(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[list[str], list[int]]:
    """Whole texts and ratings to learn from: by rating the ids of least hash, at most SAMPLE_TOXIC and SAMPLE_CLEAN, never held-out
    ones. Only the number of rows is bounded, so what the driver holds grows with the sampled texts' length alone."""
    rated = labels.where(F.col("toxic").isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col))).select(F.col(id_col).alias("_id"), F.col("toxic").cast("int").alias("_y")).distinct()
    part = lambda y, n: rated.where(F.col("_y") == y).orderBy(F.xxhash64("_id"), "_id").limit(n)
    ids = part(1, SAMPLE_TOXIC).unionByName(part(0, SAMPLE_CLEAN))
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_t")).join(F.broadcast(ids), "_id").where("_t is not null").collect()
    rows = sorted((r["_id"], r["_t"], r["_y"]) for r in rows)
    return [t for _, t, _ in rows], [y for _, _, y in rows]


SCORE_SCHEMA = "doc_id long, score double, expected_toxic_tokens double, spans array<struct<start:int,end:int,marginal:double>>"


def scorer(shared):
    """texts -> (score, marginals) of each, lower-cased texts beside them; for use in a task."""
    field, cache = Field(*shared.value), {}
    b0, b1, b2 = field.link

    def score(texts: list[str | None]) -> tuple[list[float], list[np.ndarray], list[str]]:
        low = [lowered(t) for t in texts]
        m = marginals([score_words(field, WORD.findall(t), cache) for t in low], field.pair, field.start)
        odds = [summary(p) for p in m]
        return [1 / (1 + math.exp(-max(-30.0, min(30.0, b0 + b1 * top + b2 * mass)))) for top, mass in odds], m, low

    return score


def share(docs: DataFrame, field: Field):
    """The field on every executor: DIM floats, whatever the data."""
    return docs.sparkSession.sparkContext.broadcast((field.weights, field.pair, field.start, field.link))


def spans_of(text: str, p: np.ndarray) -> list[dict]:
    """Runs of tokens with marginal >= 0.5 as character offsets."""
    runs, last = [], -2
    if len(p) and p.max() >= 0.5:
        for i, w in enumerate(WORD.finditer(text)):
            if p[i] >= 0.5:
                if last == i - 1:
                    runs[-1] = {"start": runs[-1]["start"], "end": w.end(), "marginal": max(runs[-1]["marginal"], float(p[i]))}
                else:
                    runs.append({"start": w.start(), "end": w.end(), "marginal": float(p[i])})
                last = i
    return runs


def toxicity_scores(docs: DataFrame, field: Field, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score in 0..1, expected toxic tokens, and spans (character offsets of runs of tokens with marginal >= 0.5).

    Whole texts, row by row, offsets in the text as given; null and empty texts have no tokens and get the field's base score.
    Repeated rows repeat their result, null ids stay null, an empty table gives an empty result.
    """
    shared = share(docs, field)
    span_type = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("marginal", pa.float64())]))

    def run(batches):
        score = scorer(shared)
        for part in slices(batches, 500):
            scores, m, texts = score(part.column(1).to_pylist())
            spans = [spans_of(t, p) for t, p in zip(texts, m)]
            yield pa.record_batch([part.column(0), pa.array(scores, pa.float64()), pa.array([float(p.sum()) for p in m], pa.float64()), pa.array(spans, span_type)], ["doc_id", "score", "expected_toxic_tokens", "spans"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, SCORE_SCHEMA)


def without_toxic(docs: DataFrame, field: Field, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose text scores under the threshold. Each row decides for itself, so nothing is joined or shuffled."""
    shared = share(docs, field)

    def run(batches):
        score = scorer(shared)
        for part in slices(batches, 500):
            scores, _, _ = score(part.column(part.schema.get_field_index(text_col)).to_pylist())
            yield part.filter(pa.array([s < threshold for s in scores], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def trained(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> Field:
    return fit(*sample(docs, labels))


def op10_toxic_span_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = toxicity_scores(docs, trained(spark, docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), F.size("spans").alias("n_spans"), "spans")
