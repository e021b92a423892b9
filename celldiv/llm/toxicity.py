"""Toxicity from nearest labelled examples by exact TF-IDF cosine.

Terms are words, and beginnings of words that go with the label. Every word that occurs in `least` examples or more
belongs to the vocabulary, whatever the label, so every text in prose meets the index. A term's weight is its
TF-IDF times a relevance: FLOOR for any term, more for one that goes with the label (the root of its
likelihood ratio). The examples' vectors lie in an index cut into blocks of like vectors:

* rare and relevant terms have inverted lists, whose sums give the exact part of a similarity;
* frequent terms of little weight have their weights stored by block, with the largest one per term and block.

A block's greatest exact part plus its frequent terms' largest weights bounds every similarity in it. Blocks are
opened from the greatest bound down until none can hold a nearer example: the k nearest are
exact. They vote with weights that grow as the distance falls, and the vote is calibrated by
isotonic regression on the examples, each judged by the others.

At most `max_examples` labelled rows make the examples (those of least hash): a documented bound, which also bounds
the vocabulary and the index that are broadcast. Labels of one document that disagree count by majority, ties as
toxic; null labels are ignored; a doc_id that several documents have lends its label to each.

Defined results: null and empty texts, and texts without a known term, get the rate of such examples, zero if there are
none; without any examples every score is 0; repeated rows are scored each. Labels, lang, source
and doc_id are no inputs of a score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MAX_EXAMPLES, LEAST = 4_000, 3
NEAREST, BLOCK, BATCH = 15, 64, 64
LIMIT = 0.7
BEGINNINGS = (4, 5, 6, 8)
#: Relevance of any term; likelihood ratio from which a term counts as relevant; share of the examples from which a term is frequent.
FLOOR, GAIN, FREQUENT = 0.3, 12.0, 1 / 16
WORD = re.compile(r"[^\W\d_]+")


def forms(word: str) -> list[str]:
    """A word as terms: itself, and its beginnings (marked by a following '*')."""
    return [word, *[word[:k] + "*" for k in BEGINNINGS if len(word) > k]]


def terms(text: str | None) -> Counter:
    out: Counter = Counter()
    for w, n in Counter(WORD.findall((text or "").lower())).items():
        for t in forms(w):
            out[t] += n
    return out


def examples(docs: DataFrame, labels: DataFrame, max_examples: int = MAX_EXAMPLES) -> DataFrame:
    """doc_id, text, toxic of the labelled documents of least hash, at most max_examples labels."""
    given = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").alias("__id")).agg((F.avg("toxic") >= 0.5).cast("int").alias("toxic"))
    chosen = given.orderBy(F.xxhash64("__id"), "__id").limit(max_examples)
    shown = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("__id")).select("doc_id", "text", "toxic")
    return shown.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_examples)  # ids that repeat do not lift the bound


class Vocabulary:
    """term -> number, and the weight of each number; turns texts into vectors of length one."""

    def __init__(self, known: dict[str, int], weight: np.ndarray, relevant: np.ndarray) -> None:
        self.known, self.weight, self.relevant = known, weight, relevant
        self.numbers: dict[str, tuple[int, ...]] = {}

    def __getstate__(self) -> dict:
        return self.__dict__ | {"numbers": {}}

    def vector(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        found: dict[int, int] = {}
        for w, n in Counter(WORD.findall((text or "").lower())).items():
            if (own := self.numbers.get(w)) is None:
                if len(self.numbers) > 300_000:
                    self.numbers.clear()
                own = self.numbers[w] = tuple(self.known[t] for t in forms(w) if t in self.known)
            for t in own:
                found[t] = found[t] + n if t in found else n
        if not found:
            return np.empty(0, np.int32), np.empty(0)
        at = np.fromiter(found, np.int32, len(found))
        order = np.argsort(at)
        at = at[order]
        w = (1 + np.log(np.fromiter(found.values(), np.float64, len(found))[order])) * self.weight[at]
        return at, w / np.linalg.norm(w)


def learn_terms(shown: DataFrame, least: int = LEAST) -> Vocabulary:
    """All words, and the relevant beginnings, of at least `least` examples, with IDF times relevance."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found: tuple[Counter, Counter] = (Counter(), Counter())
            size = [0, 0]
            for text, toxic in zip(batch.column(0), batch.column(1).to_pylist()):
                found[toxic].update(terms(text.as_py()).keys())
                size[toxic] += 1
            names = ["", *(found[0].keys() | found[1].keys())]
            yield pa.RecordBatch.from_arrays([pa.array(names), pa.array([size[0], *[found[0][t] for t in names[1:]]], pa.int64()), pa.array([size[1], *[found[1][t] for t in names[1:]]], pa.int64())], ["term", "clean", "toxic"])

    counts = shown.select("text", "toxic").mapInArrow(count, "term string, clean long, toxic long").groupBy("term").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    rows = counts.where((F.col("term") == "") | (F.col("clean") + F.col("toxic") >= least)).toPandas()  # bounded by the examples
    sizes = rows[rows.term == ""]
    n0, n1 = (int(sizes.clean.sum()), int(sizes.toxic.sum()))
    rows = rows[rows.term != ""].sort_values("term")
    a, b, n = rows.toxic.to_numpy(np.float64), rows.clean.to_numpy(np.float64), float(n0 + n1)
    df = a + b
    gain = np.zeros(len(rows))
    with np.errstate(divide="ignore", invalid="ignore"):
        for seen, expected in ((a, df * n1 / max(n, 1)), (b, df * n0 / max(n, 1)), (n1 - a, (n - df) * n1 / max(n, 1)), (n0 - b, (n - df) * n0 / max(n, 1))):
            gain += np.where(seen > 0, 2 * seen * np.log(seen / expected), 0.0)
    relevant = (a * n > df * n1) & (gain > GAIN)
    weight = (np.log((n + 1) / (df + 1)) + 1) * (FLOOR + np.where(relevant, np.sqrt(np.maximum(gain - GAIN, 0)), 0.0))
    stays = relevant | ~rows.term.str.endswith("*").to_numpy(bool)
    return Vocabulary({t: i for i, t in enumerate(rows.term[stays])}, weight[stays], relevant[stays])


class BlockMaxIndex:
    """The examples' vectors in blocks, like ones together; toxic[i] tells the label of example i."""

    def __init__(self, vectors: list[tuple[np.ndarray, np.ndarray]], toxic: list[int], relevant: np.ndarray, block: int = BLOCK, frequent: float = FREQUENT) -> None:
        n, n_terms = len(vectors), len(relevant)
        self.block, self.n, self.blocks = block, n, -(-n // block)
        sizes = np.array([len(at) for at, _ in vectors], np.int64)
        term = np.concatenate([at for at, _ in vectors]).astype(np.int64) if n else np.empty(0, np.int64)
        weight = np.concatenate([w for _, w in vectors]) if n else np.empty(0)
        doc = np.repeat(np.arange(n), sizes)
        df = np.bincount(term, minlength=n_terms)
        often = (df > frequent * n) & ~relevant
        # like vectors share blocks: by the heaviest relevant term, then by the heaviest frequent one
        heads = np.full((n, 2), -1)
        for i, (at, w) in enumerate(vectors):
            for j, kind in enumerate((relevant, often)):
                if kind[at].any():
                    heads[i, j] = at[np.where(kind[at], w, -1.0).argmax()]
        self.order = np.lexsort((np.arange(n), heads[:, 1], heads[:, 0]))  # place -> example
        self.place = np.empty(n, np.int64)
        self.place[self.order] = np.arange(n)
        self.toxic = np.array(toxic, np.float64)[self.order] if n else np.empty(0)
        doc = self.place[doc]
        self.column = np.full(n_terms, -1)
        self.column[often] = np.arange(often.sum())
        far = often[term]
        self.often = (doc[far].astype(np.int32), self.column[term[far]].astype(np.int32), weight[far].astype(np.float32))
        by = np.lexsort((doc[~far], term[~far]))
        self.doc, self.weight = doc[~far][by].astype(np.int32), weight[~far][by]
        self.begin = np.searchsorted(term[~far][by], np.arange(n_terms + 1))
        self._made: tuple[np.ndarray, np.ndarray] | None = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_made": None}

    def _stored(self) -> tuple[np.ndarray, np.ndarray]:
        """Frequent weights by place and column, and the largest per block; made where they are used."""
        if self._made is None:
            d, c, w = self.often
            dense = np.zeros((self.blocks * self.block, int(self.column.max(initial=-1)) + 1), np.float32)
            dense[d, c] = w
            self._made = dense, np.ascontiguousarray(dense.reshape(self.blocks, self.block, -1).max(axis=1).T)
        return self._made

    def nearest(self, queries: list[tuple[np.ndarray, np.ndarray]], k: int, without: list[int] | None = None) -> tuple[list[list[tuple[float, int]]], int]:
        """Per query (cosine, example) of the k nearest, with all that are as near as the last of them, and the blocks opened in all.

        without[i] leaves that example out of query i's answer. Similarities of zero are none."""
        dense, most = self._stored()
        size, m = self.block, len(queries)
        exact = np.zeros((m, self.blocks * size))
        common = np.zeros((m, dense.shape[1]), np.float32)
        for i, (at, w) in enumerate(queries):
            column = self.column[at]
            common[i, column[column >= 0]] = w[column >= 0]
            at, w = at[column < 0], w[column < 0]
            first, last = self.begin[at], self.begin[at + 1]
            long = last - first
            if long.sum():
                spots = np.repeat(first - np.r_[0, np.cumsum(long)[:-1]], long) + np.arange(long.sum())
                exact[i] = np.bincount(self.doc[spots], weights=self.weight[spots] * np.repeat(w, long), minlength=exact.shape[1])
            if without is not None:
                exact[i, self.place[without[i]]] = -np.inf
        exact[:, self.n:] = -np.inf
        bound = exact.reshape(m, self.blocks, size).max(axis=2) + common @ most + 1e-5
        least, kept, opened = np.full(m, 1e-9), [np.empty((2, 0)) for _ in range(m)], 0
        todo, turn = bound > 0, np.argsort(-bound, axis=1)
        for step in range(self.blocks):
            # every query's best blocks first, then the others, block by block for all queries that still need one
            if step < 2:
                wanted = np.zeros_like(todo)
                wanted[np.arange(m), turn[:, step]] = True
                wanted &= todo
            else:
                wanted = todo & (bound >= least[:, None])
            for b in np.flatnonzero(wanted.any(axis=0)):
                some = np.flatnonzero(wanted[:, b] & (bound[:, b] >= least))
                if not len(some):
                    continue
                rows = slice(b * size, (b + 1) * size)
                sums = exact[some, rows] + common[some] @ dense[rows].T
                opened += len(some)
                for i, s in zip(some, sums):
                    good = np.flatnonzero(s > least[i] - 1e-5)
                    if len(good):
                        both = np.concatenate([kept[i], [s[good], good + b * size]], axis=1)
                        if both.shape[1] > k:
                            least[i] = max(least[i], np.partition(both[0], -k)[-k])
                            both = both[:, both[0] > least[i] - 1e-5]
                        kept[i] = both
            todo &= ~wanted
            if step >= 2:
                break
        out = []
        for i in range(m):
            places = np.sort(kept[i][1].astype(np.int64))
            # once more, in double precision and one order, so that batches do not matter
            cosine = exact[i, places] + np.array([float((dense[p].astype(np.float64) * common[i]).sum()) for p in places]) if len(places) else np.empty(0)
            got = sorted((-round(min(float(c), 1.0), 6), int(self.order[p])) for c, p in zip(cosine, places) if c > 1e-9)
            out.append([(-c, e) for c, e in got if c <= got[min(k, len(got)) - 1][0]])
        return out, opened


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Points (mean x, share of y) of pools whose shares rise; a pool of few examples leans to the middle.

    Pools are joined until their leaning shares rise, so lines between the points never fall."""
    order = np.argsort(x, kind="stable")
    pools: list[list[float]] = []
    share = lambda p: (p[1] + 0.5) / (p[2] + 1)
    at = 0
    xs, ys = x[order], y[order]
    while at < len(xs):
        end = int(np.searchsorted(xs, xs[at], side="right"))
        pools.append([float(xs[at:end].sum()), float(ys[at:end].sum()), float(end - at)])
        at = end
        while len(pools) > 1 and share(pools[-2]) >= share(pools[-1]):
            top = pools.pop()
            pools[-1] = [a + b for a, b in zip(pools[-1], top)]
    return np.array([p[0] / p[2] for p in pools]), np.array([share(p) for p in pools])


class Model:
    """Everything a task needs to score texts; its size is bounded by max_examples."""

    def __init__(self, words: Vocabulary, index: BlockMaxIndex, ids: list[int], toxic: list[int], none: float, k: int) -> None:
        self.words, self.index, self.ids, self.toxic, self.none, self.k = words, index, ids, toxic, none, k
        self.line = (np.zeros(1), np.full(1, none))
        self.seen: dict[bytes, tuple] = {}

    def __getstate__(self) -> dict:
        return self.__dict__ | {"seen": {}}

    def vote(self, found: list[tuple[float, int]]) -> float:
        """The toxic share among the nearest examples, near ones counting more."""
        weights = [1 / (1.05 - c) for c, _ in found]
        return sum(w * self.toxic[e] for w, (_, e) in zip(weights, found)) / sum(weights) if found else self.none

    def scores(self, texts: list[str | None]) -> list[tuple[float, list[int], list[float]]]:
        """Calibrated scores, and as evidence the nearest examples' ids and cosines."""
        keys = [xxhash.xxh3_128_digest((t or "").encode("utf-8", "surrogatepass")) for t in texts]
        fresh = {key: t for key, t in zip(keys, texts) if key not in self.seen}
        if len(self.seen) + len(fresh) > 50_000:
            self.seen.clear()
            fresh = dict(zip(keys, texts))
        vectors = {key: self.words.vector(t) for key, t in fresh.items()}
        asked = [key for key, (at, _) in vectors.items() if len(at) and self.index.n]
        self.seen |= {key: (self.none, [], []) for key in vectors}
        for begin in range(0, len(asked), BATCH):
            some = asked[begin:begin + BATCH]
            for key, found in zip(some, self.index.nearest([vectors[key] for key in some], self.k)[0]):
                value = float(np.interp(self.vote(found), *self.line)) if found else self.none
                self.seen[key] = value, [self.ids[e] for _, e in found[:self.k]], [c for c, _ in found[:self.k]]
        return [self.seen[key] for key in keys]


def fit(docs: DataFrame, labels: DataFrame, max_examples: int = MAX_EXAMPLES, k: int = NEAREST) -> Model:
    """labels: the rows to learn from (doc_id, toxic)."""
    from celldiv.llm.common import persisted

    spark = docs.sparkSession
    shown = persisted(examples(docs, labels, max_examples).repartition(int(spark.conf.get("spark.sql.shuffle.partitions", "200"))))
    words = learn_terms(shown)
    shared = spark.sparkContext.broadcast(words)

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(*shared.value.vector(t.as_py()), xxhash.xxh64_intdigest((t.as_py() or "").encode("utf-8", "surrogatepass")) >> 1) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([r[2] for r in rows], pa.int64()), pa.array([r[0].tobytes() for r in rows], pa.binary()), pa.array([r[1].tobytes() for r in rows], pa.binary())], ["doc_id", "toxic", "tie", "at", "w"])

    got = shown.select(F.col("doc_id").cast("long"), "text", F.col("toxic").cast("int")).mapInArrow(vectors, "doc_id long, toxic int, tie long, at binary, w binary").collect()  # bounded by max_examples
    rows = sorted(((r["doc_id"], r["tie"], r["toxic"], np.frombuffer(r["at"], np.int32), np.frombuffer(r["w"])) for r in got), key=lambda r: r[:3])
    shared.destroy()
    del got
    none = [r[2] for r in rows if not len(r[3])]
    rows = [r for r in rows if len(r[3])]
    toxic = [r[2] for r in rows]
    index = BlockMaxIndex([r[3:] for r in rows], toxic, words.relevant)
    model = Model(words, index, [r[0] for r in rows], toxic, sum(none) / (len(none) + 1), k)
    if not rows:
        return model
    # every example judged by the others, by the tasks
    held, own = spark.sparkContext.broadcast((model, [r[3:] for r in rows])), spark.range(len(rows))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told, vectors_ = held.value
        for batch in batches:
            numbers = batch.column(0).to_pylist()
            for begin in range(0, len(numbers), BATCH):
                some = numbers[begin:begin + BATCH]
                found = told.index.nearest([vectors_[i] for i in some], told.k, some)[0]
                yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array([told.vote(f) for f in found], pa.float64())], ["id", "vote"])

    votes = {r["id"]: r["vote"] for r in own.mapInArrow(judge, "id long, vote double").collect()}  # one number per example
    held.destroy()
    model.line = isotonic(np.array([votes[i] for i in range(len(rows))]), np.array(toxic, np.float64))
    return model


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score, evidence (example ids), cosines; one row per document row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 4 * BATCH):
                part = batch.slice(begin, 4 * BATCH)
                got = shared.value.scores(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([g[0] for g in got], pa.float64()), pa.array([g[1] for g in got], pa.list_(pa.int64())), pa.array([g[2] for g in got], pa.list_(pa.float64()))], ["doc_id", "score", "evidence", "cosines"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, score double, evidence array<long>, cosines array<double>")


def reject(docs: DataFrame, model: Model, limit: float = LIMIT) -> DataFrame:
    """The documents, all columns, that score below the limit."""
    shared, kind = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    where = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 4 * BATCH):
                part = batch.slice(begin, 4 * BATCH)
                yield part.filter(pa.array([g[0] < limit for g in shared.value.scores(part.column(where).to_pylist())], pa.bool_()))

    return docs.mapInArrow(run, kind)
