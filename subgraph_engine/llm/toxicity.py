"""Toxic passages by maximum-scoring segments of token log-odds, calibrated by extreme values.

Training takes a bounded sample of labelled documents. Three quarters of it give each token (a run
of letters, a to z in lower case) its log-odds of lying in toxic rather than in clean documents,
with a Dirichlet prior in proportion to the token's share of all. The lexicon is of tokens whose
documents are toxic more often than all are, by a likelihood ratio over exp(evidence). All other
tokens cost ``DRIFT`` or more, so that clean text loses on average. A token scores the same wherever
it stands and whatever came before it.

Along a document, one linear scan finds every maximal segment of positive score. Chance gives the
best segment of n clean tokens an extreme-value law: P(S > x) = 1 - exp(-K n exp(-lambda x)), with
lambda from the clean tokens' scores, and K the likeliest for the best segments of the clean documents
in the remaining quarter of the sample. A segment is significant if its probability is below
``SIGNIFICANT``. That quarter also maps a document's evidence (the best segment against the law, and
how many are significant) to a probability, and settles the evidence that the lexicon asks for: the
one of ``EVIDENCE`` with the least loss when one half of the quarter judges the other. So no limit
depends on rows that are held out.

Labels, ids, languages and sources are no inputs of a score. Null text counts as empty and scores
as a text without evidence. Without toxic or clean rows to learn from, every score is the share of
toxic rows. Repeated texts count once in training. Texts of any length; one document at a time.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.llm.common import written
from subgraph_engine.llm.hashing import NOT_LETTERS, blocks, word_hashes

#: Labelled rows that are learned from at most.
SAMPLE = 20_000
#: Evidence that a lexicon may ask of its tokens.
EVIDENCE = (4.0, 6.0, 8.0, 11.0, 14.0, 20.0)
#: Prior documents for each token at least, and in all; the highest score of a token, and the least cost of others.
PRIOR_LEAST, PRIOR_ALL, MOST_SCORE, DRIFT = 0.5, 100.0, 10.0, 0.1
SIGNIFICANT, THRESHOLD = 0.01, 0.3


def maximal_segments(at: np.ndarray, scores: np.ndarray, drift: float) -> list[tuple[float, int, int]]:
    """All maximal segments (score, first, last token) of positive tokens at ``at`` among tokens that cost ``drift``.

    One pass with a stack of candidates, each with the sum before it and up to its end.
    """
    stack: list[tuple[float, float, int, int]] = []
    total, last = 0.0, -1
    for k, s in zip(at.tolist(), scores.tolist(), strict=True):
        total -= drift * (k - last - 1)
        left, first = total, k
        total += s
        last = k
        right = total
        while True:
            j = len(stack) - 1
            while j >= 0 and stack[j][0] >= left:
                j -= 1
            if j < 0 or stack[j][1] >= right:
                stack.append((left, right, first, k))
                break
            left, first = stack[j][0], stack[j][2]
            del stack[j:]
    return [(right - left, first, end) for left, right, first, end in stack]


@dataclass(frozen=True)
class Model:
    tokens: np.ndarray  # sorted hashes
    scores: np.ndarray
    rate: float  # lambda
    scale: float  # ln K
    drift: float  # what a token outside the lexicon costs
    weights: tuple[float, float, float]  # of one, the best segment's evidence, the number of significant ones

    def segments(self, hashes: np.ndarray) -> list[tuple[float, int, int]]:
        if not len(self.tokens) or not len(hashes):
            return []
        at = np.minimum(np.searchsorted(self.tokens, hashes), len(self.tokens) - 1)
        hit = np.flatnonzero(self.tokens[at] == hashes)
        if not len(hit):
            return []
        return maximal_segments(hit, self.scores[at[hit]], self.drift)

    def judged(self, hashes: np.ndarray) -> tuple[float, list[tuple[int, int, float]]]:
        """The best segment's excess over chance, and all significant ones (first and last token, score)."""
        found = self.segments(hashes)
        if not found:
            return 0.0, []
        excess = self.excess(np.array([s for s, _, _ in found]), len(hashes))
        return self.above(excess), [(first, last, s) for (s, first, last), x in zip(found, self.sure(excess), strict=True) if x]

    def excess(self, scores: np.ndarray, n: int) -> np.ndarray:
        """Segments' scores in units of the law, over what chance gives the best of n tokens."""
        return self.rate * scores - self.scale - np.log(max(n, 1))

    @staticmethod
    def above(excess: np.ndarray) -> float:
        return float(np.clip(excess.max(initial=-3.0), -3, 30)) + 3

    @staticmethod
    def sure(excess: np.ndarray) -> np.ndarray:
        return -np.expm1(-np.exp(-excess)) < SIGNIFICANT

    def evidence(self, hashes: np.ndarray) -> tuple[float, int]:
        """The best segment's excess over chance, and how many segments are significant."""
        best, spans = self.judged(hashes)
        return best, len(spans)

    def score(self, hashes: np.ndarray) -> float:
        return self.probability(*self.evidence(hashes))

    def probability(self, best: float, n: int) -> float:
        x = self.weights[0] + self.weights[1] * best + self.weights[2] * np.log1p(n)
        return float(1 / (1 + np.exp(-np.clip(x, -30, 30))))


def _rate(scores: np.ndarray, shares: np.ndarray, drift: float) -> float:
    """The positive root of sum(share exp(rate score)) + rest exp(-rate drift) = 1."""
    rest = 1 - shares.sum()
    low, high = 1e-6, 50.0
    for _ in range(100):
        mid = (low + high) / 2
        if (shares * np.exp(mid * scores)).sum() + rest * np.exp(-mid * drift) > 1:
            high = mid
        else:
            low = mid
    return max(low, 1e-3)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05) -> np.ndarray:
    """Weights by Newton's method; ``ridge`` keeps them finite where the classes are apart."""
    w, keep = np.zeros(x.shape[1]), np.diag([1e-3, *[ridge] * (x.shape[1] - 1)])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + keep, x.T @ (p - y) + keep @ w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def train(docs: DataFrame, labels: DataFrame, learn: F.Column, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Model:
    """The model of labelled rows where ``learn`` (a condition on ``id``) holds, ``sample`` of them at most."""
    rows = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("toxic")).where(learn & F.col("id").isNotNull() & F.col("toxic").isin(0, 1))
    rows = rows.groupBy("id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("id"), "id").limit(sample)
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    rows = texts.join(F.broadcast(rows), "id").withColumn("name", F.xxhash64("text")).dropDuplicates(["name", "toxic"])
    rows = written(rows.withColumn("fold", F.when(F.pmod("name", F.lit(4)) == 3, "fit").otherwise("count")), "toxicity_sample")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in blocks(batch, 0):
                hashes, at = word_hashes(part.column(0), NOT_LETTERS)
                toxic = part.column(1).to_numpy()
                own = [np.unique(hashes[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
                every = np.concatenate(own) if own else np.zeros(0, "<u8")
                bad = np.repeat(toxic, [len(x) for x in own])
                keys, back = np.unique(every, return_inverse=True)
                columns = [pa.array(keys.view("<i8"), pa.int64()), pa.array(np.bincount(back, bad, len(keys)).astype("<i8")), pa.array(np.bincount(back, 1 - bad, len(keys)).astype("<i8"))]
                yield pa.RecordBatch.from_arrays(columns, names=["token", "bad", "good"])

    totals = {r["toxic"]: r["n"] for r in rows.where("fold = 'count'").groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    bad, good = totals.get(1, 0), totals.get(0, 0)
    share = (bad + 0.5) / (bad + good + 1)
    plain = (float(np.log(share / (1 - share))), 0.0, 0.0)
    if not bad or not good:
        return Model(np.zeros(0, "<u8"), np.zeros(0), 1.0, 0.0, DRIFT, plain)
    counted = rows.where("fold = 'count'").select("text", "toxic").mapInArrow(count, "token long, bad long, good long").groupBy("token").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    prior = F.greatest(F.lit(PRIOR_LEAST), (F.col("bad") + F.col("good")) * (PRIOR_ALL / (bad + good)) * F.lit(0.01))
    y, n = F.col("bad") + prior, F.col("good") + prior
    odds = F.log(y / (F.lit(bad + 2 * PRIOR_LEAST) - F.least(F.col("bad"), F.lit(bad - 0.0)) + prior)) - F.log(n / (F.lit(good + 2 * PRIOR_LEAST) - F.col("good") + prior))
    both, base = F.col("bad") + F.col("good"), bad / (bad + good)
    evidence = F.col("bad") * F.log(F.col("bad") / both / base) + F.when(F.col("good") > 0, F.col("good") * F.log(F.col("good") / both / (1 - base))).otherwise(0.0)
    judged = counted.where(F.col("bad") > base * both).select("token", "good", odds.alias("odds"), evidence.alias("evidence"))
    # each such token lies in several toxic documents of the sample, which bounds their number
    found = judged.where((F.col("odds") > 0) & (F.col("evidence") > EVIDENCE[0])).collect()
    lexicon = np.array(sorted((r["token"] & (2**64 - 1), min(r["odds"], MOST_SCORE), r["good"], r["evidence"]) for r in found), dtype=[("t", "<u8"), ("s", "f8"), ("g", "f8"), ("e", "f8")])

    def drafted(least: float) -> Model:
        own = lexicon[lexicon["e"] > least]
        # how often lexicon tokens turn up in clean text, in documents and so roughly in tokens of 100 words each
        shares = (own["g"] + 0.1) / (good * 100 + 1)
        drift = max(DRIFT, 2 * float((own["s"] * shares).sum()))
        return Model(own["t"], own["s"], _rate(own["s"], shares, drift) if len(own) else 1.0, 0.0, drift, plain)

    drafts = [drafted(x) for x in EVIDENCE]

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in blocks(batch, 0):
                hashes, at = word_hashes(part.column(0), NOT_LETTERS)
                scores = [[[s for s, _, _ in m.segments(hashes[a:b])] for m in drafts] for a, b in zip(at[:-1], at[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(scores, pa.list_(pa.list_(pa.float64()))), pa.array(np.diff(at), pa.int64()), part.column(1)], names=["scores", "n", "toxic"])

    fit = rows.where("fold = 'fit'").select("text", "toxic", "name").orderBy("name").drop("name")
    seen = fit.mapInArrow(features, "scores array<array<double>>, n long, toxic int").collect()
    y, n = np.array([r["toxic"] for r in seen], float), np.array([r["n"] for r in seen], float)
    if not len(y) or y.min() == y.max():
        middle = drafts[len(drafts) // 2]
        return replace(middle, weights=(plain[0], 0.3, 1.0) if len(middle.tokens) else plain)
    fitted = [_fitted(m, [np.array(r["scores"][k]) for r in seen], n, y) for k, m in enumerate(drafts)]
    return min(fitted, key=lambda x: x[0])[1]


def _fitted(draft: Model, scores: list[np.ndarray], n: np.ndarray, y: np.ndarray) -> tuple[float, Model]:
    """The model with its law and weights fitted to documents' segments, and its loss where one half judges the other."""
    best = np.array([s.max(initial=0.0) for s in scores])
    # K n exp(-lambda S) of clean documents is exponential with mean one
    clean = (y == 0) & (n > 0)
    scale = float(np.log((clean.sum() + 0.5) / ((n * np.exp(-draft.rate * best))[clean].sum() + 0.5)))
    model = replace(draft, scale=scale)
    excess = [model.excess(s, int(k)) for s, k in zip(scores, n, strict=True)]
    x = np.array([[1, model.above(e) if len(e) else 0.0, np.log1p(model.sure(e).sum())] for e in excess])
    loss, half = 0.0, np.arange(len(y)) % 2
    for k in (0, 1):
        z = np.clip(x[half != k] @ _logistic(x[half == k], y[half == k]), -30, 30)
        loss += float(np.logaddexp(0, np.where(y[half != k] > 0, -z, z)).sum())
    return loss, replace(model, weights=tuple(float(v) for v in _logistic(x, y)))


def score_documents(docs: DataFrame, model: Model, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, score, predicted, passages, spans``: all significant segments and their count.

    A span has the numbers of its first and last token (from 0) and its score; the document's score
    has no say in it.
    """
    kind = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64()), ("score", pa.float64())]))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in blocks(batch, 1):
                hashes, at = word_hashes(part.column(1), NOT_LETTERS)
                judged = [model.judged(hashes[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
                scores = np.array([model.probability(best, len(spans)) for best, spans in judged])
                passages = [len(spans) for _, spans in judged]
                spans = pa.array([[{"first": a, "last": b, "score": s} for a, b, s in own] for _, own in judged], kind)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scores, pa.float64()), pa.array((scores >= threshold).astype("<i4")), pa.array(passages, pa.int64()), spans], names=["doc_id", "score", "predicted", "passages", "spans"])

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(rows, "doc_id long, score double, predicted int, passages long, spans array<struct<first: long, last: long, score: double>>")
