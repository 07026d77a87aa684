"""Toxicity by the nearest labelled examples under exact TF-IDF cosine.

Labelled examples (at most ``EXAMPLES`` a class, chosen by a hash of doc_id) are indexed over all words
that a likelihood-ratio test ties to toxic examples, however many there are (at most as many as the examples
hold); other words weigh nothing, which is a departure from TF-IDF over all terms. Document frequencies come from every document.
The index keeps, for each word and block of examples, the largest weight: blocks are visited
from the highest bound down until no bound reaches the k-th best cosine, so the neighbours are exact.
They vote with their cosine, corrected for the sampling of classes; a logistic curve fitted on the
examples' own leave-one-out votes turns votes into probabilities. The neighbours are the evidence.

Defined results: null and empty texts and texts without indexed words get the rate of such
examples; examples with null label are ignored, several labels of one document count as its largest;
without any toxic example all scores are the smoothed base rate; repeated rows are scored one by one; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of, written

#: labelled examples a class, least likelihood ratio and example count of a word
EXAMPLES, RATIO, SUPPORT = 6000, 30.0, 4
NEIGHBOURS, BLOCK = 25, 64
#: scores a worker remembers, by the terms of a text
CACHED = 20_000
#: lengths of indexed beginnings, and the weight all vectors share, so that counts show in a cosine
PREFIXES, COMMON = (5, 6, 7), 6.0

_WORD = re.compile(r"\w+")


def words(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def terms(word: str) -> list[str]:
    """A word and its beginnings, for stems with many endings."""
    return [word, *(word[:n] + "*" for n in PREFIXES if len(word) > n)]


def _heads(vocabulary) -> frozenset:
    return frozenset(t.rstrip("*")[: PREFIXES[0] - 1] for t in vocabulary)


def _counted(text: str | None, known: frozenset, heads: frozenset) -> Counter:
    """How often each known term is in a text; most words go by their first letters alone."""
    out, n = Counter(), PREFIXES[0] - 1
    for w in words(text):
        if w[:n] in heads:
            for t in terms(w):
                if t in known:
                    out[t] += 1
    return out


def held_out(doc_id: Column) -> Column:
    """True where labels must not be learnt: crc32 of the id as text is 0 mod 5 (null ids too)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


class BlockMaxIndex:
    """Unit vectors of examples as block-max postings; ``top`` gives exact nearest neighbours."""

    def __init__(self, vectors: list[dict[int, float]], n_features: int, block: int = BLOCK):
        self.block, self.n = block, len(vectors)
        self.blocks = max(1, -(-self.n // block))
        self.most = np.zeros((n_features, self.blocks))
        self.postings: list[dict[int, tuple]] = [{} for _ in range(n_features)]
        lists: dict[tuple[int, int], list] = {}
        for e, v in enumerate(vectors):
            for f, w in v.items():
                lists.setdefault((f, e // block), []).append((e % block, w))
        for (f, b), p in lists.items():
            at, w = np.array([x for x, _ in p]), np.array([x for _, x in p])
            self.postings[f][b] = (at, w)
            self.most[f, b] = w.max()

    def top(self, q: dict[int, float], k: int, skip: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """(examples, cosines) of the k nearest with cosine over 0; ties by example number."""
        bound = sum(w * self.most[f] for f, w in q.items())
        if np.isscalar(bound):
            return np.zeros(0, np.int64), np.zeros(0)
        best_e, best_s = np.zeros(0, np.int64), np.zeros(0)
        for b in np.argsort(-bound, kind="stable").tolist():
            if bound[b] <= 0 or len(best_s) == k and bound[b] < best_s[-1] - 1e-12:
                break
            score = np.zeros(self.block)
            for f, w in q.items():
                if (p := self.postings[f].get(b)) is not None:
                    score[p[0]] += w * p[1]
            at = np.flatnonzero(score > 0)
            e, s = at + b * self.block, np.round(score[at], 12)
            if skip >= 0:
                s, e = s[e != skip], e[e != skip]
            best_e, best_s = np.concatenate([best_e, e]), np.concatenate([best_s, s])
            order = np.lexsort((best_e, -best_s))[:k]
            best_e, best_s = best_e[order], best_s[order]
        return best_e, best_s


class Model:
    def __init__(self, vocabulary: list[str], idf: np.ndarray, examples: list[tuple[int, int, dict[str, int]]], weight: tuple[float, float], k: int):
        self.at, self.idf, self.k = {w: i for i, w in enumerate(vocabulary)}, idf, k
        self.known, self.heads = frozenset(vocabulary), _heads(vocabulary)
        full, blank = [], [1.0, 0.5]  # so that nothing is toxic where nothing is known
        for doc, y, tf in sorted(examples, key=lambda e: (e[0], e[1])):
            if v := self.vector(tf):
                full.append((doc, y, v))
            else:
                blank[y] += weight[y]
        self.blank = blank[1] / sum(blank)
        self.ids, self.y = [d for d, _, _ in full], np.array([y for _, y, _ in full], np.int64)
        self.w = np.array([weight[y] for y in self.y]) if full else np.zeros(0)
        self.index = BlockMaxIndex([v for _, _, v in full], len(vocabulary) + 1)
        self.curve = (1.0, 0.0)
        votes = np.array([self.vote(v, skip=i)[0] for i, (_, _, v) in enumerate(full)])
        if len(votes) and 0 < self.y.sum() < len(self.y):
            self.curve = fit_curve(votes, self.y, self.w)
        self.cache: dict[tuple, float] = {}

    def vector(self, tf: dict[str, int]) -> dict[int, float]:
        v = {self.at[w]: (1 + math.log(c)) * self.idf[self.at[w]] for w, c in sorted(tf.items()) if w in self.at}
        if not v:
            return {}
        v[len(self.at)] = COMMON
        size = math.sqrt(sum(x * x for x in v.values()))
        return {f: x / size for f, x in v.items()}

    def vote(self, v: dict[int, float], skip: int = -1) -> tuple[float, np.ndarray]:
        e, s = self.index.top(v, self.k, skip)
        m = s * self.w[e]
        return float((m @ self.y[e] + 0.5 * self.blank) / (m.sum() + 0.5)), e

    def counts(self, text: str | None) -> dict[str, int]:
        return _counted(text, self.known, self.heads)

    def score(self, text: str | None) -> float:
        tf = self.counts(text)
        if not tf:
            return self.blank
        key = tuple(sorted(tf.items()))
        if key not in self.cache:
            if len(self.cache) > CACHED:
                self.cache.clear()
            self.cache[key] = curve(self.vote(self.vector(tf))[0], self.curve)
        return self.cache[key]

    def evidence(self, text: str | None) -> list[tuple[int, int]]:
        """(doc_id, label) of the neighbours that voted."""
        v = self.vector(self.counts(text))
        return [(self.ids[i], int(self.y[i])) for i in self.vote(v)[1]] if v else []


def curve(vote: float, ab: tuple[float, float]) -> float:
    x = math.log(vote / (1 - vote)) if 0 < vote < 1 else math.copysign(30.0, vote - 0.5)
    return 1 / (1 + math.exp(-max(-30.0, min(30.0, ab[0] * x + ab[1]))))


def fit_curve(votes: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[float, float]:
    """Weighted logistic fit of labels on log odds of votes, with a weak pull to (1, 0)."""
    v = np.clip(votes, 1e-6, 1 - 1e-6)
    x = np.stack([np.log(v / (1 - v)), np.ones(len(v))], 1)
    b, rest = np.array([1.0, 0.0]), np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        g = x.T @ (w * (y - p)) - (b - rest)
        h = (x * (w * p * (1 - p))[:, None]).T @ x + np.eye(2)
        step = np.linalg.solve(h, g)
        b = b + np.clip(step, -1, 1)
        if abs(step).max() < 1e-9:
            break
    return (float(max(b[0], 0.05)), float(b[1]))


def _emit(columns: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))


def train(docs: DataFrame, labels: DataFrame, examples: int = EXAMPLES, k: int = NEIGHBOURS) -> Model:
    """Fit on labels outside the held-out fold; document frequencies over all ``docs``."""
    usable = labels.where(labels["toxic"].isNotNull() & ~held_out(labels["doc_id"]))
    usable = usable.groupBy(usable["doc_id"].cast("long").alias("__id")).agg(F.max("toxic").cast("int").alias("__toxic"))
    usable = written(usable.where("__toxic in (0, 1)"), "labels")
    sizes = {y: n for y, n in usable.groupBy("__toxic").count().collect()}
    order = [F.xxhash64("__id"), F.col("__id")]
    some = usable.where("__toxic = 1").orderBy(*order).limit(examples)
    some = some.unionByName(usable.where("__toxic = 0").orderBy(*order).limit(examples))
    some = written(some, "examples")  # at most 2 x examples rows, so it may be broadcast
    mine = docs.select(docs["doc_id"].cast("long").alias("__id"), text_of(docs).alias("__text")).join(F.broadcast(some), "__id")
    mine = written(mine.dropDuplicates(["__id"]).dropDuplicates(["__text"]), "labelled")

    def tally(batches):
        for b in batches:
            toxic, clean = Counter(), Counter()
            for y, t in zip(b.column("__toxic").to_pylist(), b.column("__text").to_pylist()):
                (toxic if y else clean).update({x for w in set(words(t)) for x in terms(w)})
            all_words = list(toxic.keys() | clean.keys())
            yield _emit({"word": pa.array(all_words, pa.string()), "a": pa.array([toxic[w] for w in all_words], pa.int64()), "b": pa.array([clean[w] for w in all_words], pa.int64())})

    n = {y: c for y, c in mine.groupBy("__toxic").count().collect()}
    na, nb = n.get(1, 0), n.get(0, 0)
    vocabulary: list[str] = []
    if na and nb:
        seen = mine.select("__toxic", "__text").mapInArrow(tally, "word string, a long, b long")
        seen = seen.groupBy("word").agg(F.sum("a").cast("double").alias("a"), F.sum("b").cast("double").alias("b"))
        share = F.lit(na / (na + nb))
        part = lambda o, e: F.when(o > 0, o * F.log(o / e)).otherwise(0.0)
        both = F.col("a") + F.col("b")
        g2 = 2 * (part(F.col("a"), both * share) + part(F.col("b"), both * (1 - share)))
        over = F.col("a") / na > F.col("b") / nb
        top = seen.where(over & (F.col("a") >= SUPPORT)).withColumn("g2", g2).where(F.col("g2") >= RATIO)
        vocabulary = sorted(r.word for r in top.select("word").collect())  # words of a bounded set of examples
    known, heads = frozenset(vocabulary), _heads(vocabulary)

    def frequency(batches):
        df, total = Counter(), 0
        for b in batches:
            for t in b.column(0).to_pylist():
                df.update(_counted(t, known, heads).keys())
            total += b.num_rows
        df[""] = total
        yield _emit({"word": pa.array(list(df), pa.string()), "n": pa.array(list(df.values()), pa.int64())})

    df = dict(docs.select(text_of(docs).alias("text")).mapInArrow(frequency, "word string, n long").groupBy("word").agg(F.sum("n")).collect())
    total = df.get("", 0)
    idf = np.array([math.log((total + 1) / (df.get(w, 0) + 1)) + 1 for w in vocabulary])

    def vectors(batches):
        for b in batches:
            tf = [_counted(t, known, heads) for t in b.column("__text").to_pylist()]
            yield _emit({"id": b.column("__id"), "y": b.column("__toxic"), "w": pa.array([list(x) for x in tf], pa.list_(pa.string())), "c": pa.array([list(x.values()) for x in tf], pa.list_(pa.int64()))})

    got = mine.select("__id", "__toxic", "__text").mapInArrow(vectors, "id long, y int, w array<string>, c array<long>").collect()
    weight = tuple(sizes.get(y, 0) / max(1, min(examples, sizes.get(y, 0))) for y in (0, 1))
    return Model(vocabulary, idf, [(r.id, r.y, dict(zip(r.w, r.c))) for r in got], weight, k)


def toxicity(docs: DataFrame, labels: DataFrame, model: Model | None = None) -> DataFrame:
    """One row per row of ``docs``: doc_id, held_out, score, predicted."""
    model = model or train(docs, labels)

    def run(batches):
        for b in batches:
            s = [model.score(t) for t in b.column(2).to_pylist()]
            yield _emit({"doc_id": b.column(0), "held_out": b.column(1), "score": pa.array(s, pa.float64())})

    rows = docs.select(docs["doc_id"].alias("doc_id"), held_out(docs["doc_id"]).alias("held_out"), text_of(docs).alias("text"))
    kind = dict(rows.dtypes)["doc_id"]
    out = rows.mapInArrow(run, f"doc_id {kind}, held_out boolean, score double")
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with their columns; each row is judged as it passes."""
    model = train(docs, labels)
    return docs.where(_scorer(model)(text_of(docs)) < threshold)


def _scorer(model: Model):
    import pandas as pd

    def score(texts: pd.Series) -> pd.Series:
        return texts.map(model.score).astype(float)

    score.__annotations__ = {"texts": pd.Series, "return": pd.Series}
    return F.pandas_udf(score, "double")
