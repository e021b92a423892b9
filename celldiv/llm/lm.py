"""Language-model scores by deleted interpolation of word bigrams.

P(w | h) = a * c(hw)/c(h) + b * c(w)/N + c * base(w), where (a, b, c) depend on the bucket of the
context's frequency (powers of two) and are learned by expectation-maximisation on a part of the
training documents whose counts are deleted for that. All counts are over all training documents.

Texts stay where they are read. A task folds its texts to blocks: the sequence of word codes, and
the block's distinct words and bigrams as sorted 64-bit hashes with their counts. The hashes travel
once, by ranges of the hash, to where they are added up over all blocks, and only the sums
travel back to the block. The number of ranges follows the bytes of text. So a frequent word or pair is one row per block, whatever its count,
and both shuffles hold packed columns, not a row per token.

Defined results: a null text is empty (one token, the end); a null doc_id counts as the empty id, is held
out, and is returned as null; repeated rows are counted and scored each; with no training documents
every score is that of an empty model. Extra columns are not read.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.llm.common import persisted

FOLDS, HELD_OUT, DELETED = 10, 0, 1
BLOCK_TOKENS = 4_200_000
#: Bytes of text for each range of hashes (one is added up in memory at a time) and for each task that adds up.
RANGE_BYTES, TASK_BYTES = 64 << 20, 256 << 20
CONTEXT_BUCKETS = 40
ROUNDS = 15
END, START = b"", b" "  # no word is either

ROW = "kind int, block string, bucket int, data binary"
_FIELDS = [("kind", pa.int32()), ("block", pa.string()), ("bucket", pa.int32()), ("data", pa.binary())]


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, (_, t) in enumerate(_FIELDS)], [n for n, _ in _FIELDS])


def _shut(a: np.ndarray) -> tuple[str, bytes]:
    """An array as compressed byte planes; leading zero bytes then cost nothing."""
    if a.dtype == np.uint64 and len(a) and not (a & np.uint64(0xFF)).any() and a.any():
        return "56", _shut(a >> np.uint64(8))[1]
    planes = np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.dtype.itemsize).T
    return a.dtype.str, zstandard.ZstdCompressor(level=3).compress(np.ascontiguousarray(planes).tobytes())


def _open(told: tuple[str, bytes]) -> np.ndarray:
    if told[0] == "56":
        return _open(("<u8", told[1])) << np.uint64(8)
    kind = np.dtype(told[0])
    flat = np.frombuffer(zstandard.ZstdDecompressor().decompress(told[1]), np.uint8)
    return np.ascontiguousarray(flat.reshape(kind.itemsize, -1).T).view(kind).ravel()


def _shut_sorted(a: np.ndarray) -> tuple[str, bytes]:
    return _shut(np.diff(a, prepend=np.uint64(0)))


def _open_sorted(told: tuple[str, bytes]) -> np.ndarray:
    return np.cumsum(_open(told), dtype=np.uint64)


def _shut_codes(codes: np.ndarray, size: int) -> dict:
    """Codes by falling frequency, so that most are small numbers, and the order itself."""
    order = np.argsort(-np.bincount(codes, minlength=size), kind="stable")
    rank = np.empty(size, np.uint32)
    rank[order] = np.arange(size, dtype=np.uint32)
    return {"codes": _shut(rank[codes]), "order": _shut(order.astype(np.uint32))}


def _pairs(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    """One hash of two, of 56 bits at the top of 64: among 10^8 bigrams the chance of any collision is some percent,
    and a collision only adds two counts. Words keep all 64 bits."""
    x = h * np.uint64(0x9E3779B97F4A7C15) + (w ^ (w >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0x94D049BB133111EB)
    return (x ^ (x >> np.uint64(29))) & np.uint64(0xFFFFFFFFFFFFFF00)


def fold_of(doc_id: int | None, folds: int = FOLDS) -> int:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds


class _Block:
    """Codes of a block's texts, and its bigrams in the order of their hashes."""

    def __init__(self, hashes: np.ndarray, codes: np.ndarray, lengths: np.ndarray, folds: np.ndarray) -> None:
        # codes index hashes, which is sorted; the end closes each text
        self.hashes, self.codes, self.lengths, self.folds = hashes, codes, lengths, folds
        self.of_doc = np.repeat(np.arange(len(lengths), dtype=np.int32), lengths)
        before = np.empty_like(codes)
        before[1:] = codes[:-1]
        before[np.r_[0, np.cumsum(lengths)[:-1]]] = len(hashes)  # the start, which is no word
        key = before.astype(np.uint64) << np.uint64(32) | codes.astype(np.uint64)
        del before
        found, self.pair_of = np.unique(key, return_inverse=True)
        del key
        h, w = (found >> np.uint64(32)).astype(np.int64), (found & np.uint64(0xFFFFFFFF)).astype(np.int64)
        pair = _pairs(np.r_[hashes, np.uint64(xxhash.xxh64_intdigest(START))][h], hashes[w])
        order = np.argsort(pair, kind="stable")
        rank = np.empty(len(order), np.int32)
        rank[order] = np.arange(len(order))
        self.pairs, self.h, self.w, self.pair_of = pair[order], h[order], w[order], rank[self.pair_of.ravel()]

    def counts(self, of: np.ndarray, size: int, docs: np.ndarray) -> np.ndarray:
        return np.bincount(of[docs[self.of_doc]], minlength=size).astype(np.uint32)


def _gather(bits: int):
    """Texts to blocks: kind 0 the codes, kinds 1 and 2 words and bigrams of one range of hashes with their counts."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, part = 0, TaskContext.get().partitionId()
        index: dict[bytes, int] = {END: 0}
        codes: list[np.ndarray] = []
        ids: list[int | None] = []
        tokens = 0

        def close() -> Iterator[pa.RecordBatch]:
            digest = xxhash.xxh64_intdigest
            own = np.fromiter(map(digest, index), np.uint64, len(index))
            order = np.argsort(own, kind="stable")
            rank = np.empty(len(order), np.int32)
            rank[order] = np.arange(len(order))
            lengths, folds = np.array([len(c) for c in codes]), np.array([fold_of(i) for i in ids])
            block = _Block(own[order], rank[np.concatenate(codes)], lengths, folds)
            name = f"{part}-{number}"
            told = {"ids": ids, "lengths": _shut(lengths), "folds": _shut(folds.astype(np.uint8)), "hashes": _shut_sorted(block.hashes)} | _shut_codes(block.codes, len(block.hashes))
            yield _rows([(0, name, number * 7919 + part, pickle.dumps(told))])
            learnt, deleted = (folds != HELD_OUT) & (folds != DELETED), folds == DELETED
            rows = []
            for kind, hashes, of in ((1, block.hashes, block.codes), (2, block.pairs, block.pair_of)):
                counts = [block.counts(of, len(hashes), d) for d in (learnt, deleted)]
                cuts = np.searchsorted(hashes, np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)) if bits else np.empty(0, np.int64)
                for bucket, (a, b) in enumerate(zip([0, *cuts], [*cuts, len(hashes)])):
                    if b > a:
                        rows.append((kind, name, bucket, pickle.dumps((_shut_sorted(hashes[a:b]), _shut(counts[0][a:b]), _shut(counts[1][a:b])))))
            for at in range(0, len(rows), 64):
                yield _rows(rows[at:at + 64])

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                words = (text.as_py() or "").encode("utf-8", "surrogatepass").lower().split()
                got = [index.setdefault(w, len(index)) for w in words]
                got.append(0)
                codes.append(np.array(got, np.int32))
                ids.append(doc)
                tokens += len(got)
                if tokens >= BLOCK_TOKENS:
                    yield from close()
                    number, index, codes, ids, tokens = number + 1, {END: 0}, [], [], 0
        if ids:
            yield from close()

    return run


def _runs(batches: Iterator[pa.RecordBatch], *columns: str) -> Iterator[list[dict]]:
    """Rows, sorted by the columns, as lists that share their values."""
    have: list[dict] = []
    for batch in batches:
        for row in batch.to_pylist():
            if have and any(have[-1][c] != row[c] for c in columns):
                yield have
                have = []
            have.append(row)
    if have:
        yield have


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums over all blocks, sent back to each; kind 3 has the corpus's totals. Kind 0 passes."""
    for rows in _runs(batches, "route", "kind", "bucket"):
        kind, bucket = rows[0]["kind"], rows[0]["bucket"]
        if kind == 0:
            for r in rows:
                yield _rows([(0, r["block"], 0, r["data"])])
            continue
        own = [(r["block"], _open_sorted(d[0]), _open(d[1]), _open(d[2])) for r in rows for d in [pickle.loads(r.pop("data"))]]
        found, at = np.unique(np.concatenate([x[1] for x in own]), return_inverse=True)
        at = at.ravel()
        a, b = (np.bincount(at, weights=np.concatenate([x[i] for x in own]), minlength=len(found)).astype(np.uint64) for i in (2, 3))
        begin = 0
        for block, hashes, *_ in own:
            mine = at[begin:begin + len(hashes)]
            begin += len(hashes)
            yield _rows([(kind, block, bucket, pickle.dumps((_shut(a[mine]), _shut(b[mine]))))])
        if kind == 1:
            yield _rows([(3, f"totals-{bucket}", bucket, pickle.dumps((int(a.sum()), int((a > 0).sum()), int((a + b).sum()), int((a + b > 0).sum()))))])


def _assemble(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row per block: its codes and the corpus's counts of its words and bigrams; kind 4 has its deleted part."""
    for rows in _runs(batches, "block"):
        if rows[0]["kind"] == 3:
            yield _rows([(3, r["block"], 0, r["data"]) for r in rows])
            continue
        told = pickle.loads(next(r["data"] for r in rows if r["kind"] == 0))
        for kind, name in ((1, "words"), (2, "pairs")):
            parts = [[_open(x) for x in pickle.loads(r["data"])] for r in sorted((r for r in rows if r["kind"] == kind), key=lambda r: r["bucket"])]
            told[name] = [_shut(np.concatenate([p[i] for p in parts])) for i in (0, 1)]
        data = pickle.dumps(told)
        yield _rows([(0, rows[0]["block"], 0, data)])
        if held := _held_out_counts(data):
            yield _rows([(4, rows[0]["block"], 0, held)])


def _read(data: bytes) -> tuple[_Block, dict, list[np.ndarray], list[np.ndarray]]:
    told = pickle.loads(data)
    codes = _open(told["order"]).astype(np.int32)[_open(told["codes"])]
    block = _Block(_open_sorted(told["hashes"]), codes, _open(told["lengths"]), _open(told["folds"]))
    words, pairs = ([_open(x).astype(np.float64) for x in told[k]] for k in ("words", "pairs"))
    return block, told, words, pairs


def _context(words: np.ndarray, block: _Block) -> np.ndarray:
    """c(h) per bigram; the start's count is the end's, one per text."""
    end = int(np.searchsorted(block.hashes, np.uint64(xxhash.xxh64_intdigest(END))))
    return np.r_[words, words[end]][block.h]


def _bucket(c: np.ndarray) -> np.ndarray:
    return np.where(c > 0, np.minimum(np.floor(np.log2(np.maximum(c, 1))) + 1, CONTEXT_BUCKETS - 1), 0).astype(np.int64)


def _estimates(pair: np.ndarray, context: np.ndarray, word: np.ndarray, n: int, v: int) -> Iterator[np.ndarray]:
    yield pair / np.maximum(context, 1)
    yield word / max(n, 1)
    yield (word + 0.1) / (n + 0.1 * (v + 1))


def _held_out_counts(data: bytes) -> bytes | None:
    """A block's deleted bigrams: c(hw), c(h), c(w) in the rest and their count."""
    block, _, words, pairs = _read(data)
    n = block.counts(block.pair_of, len(block.pairs), block.folds == DELETED)
    at = np.flatnonzero(n)
    if not len(at):
        return None
    return pickle.dumps([_shut(x[at].astype(np.uint64)) for x in (pairs[0], _context(words[0], block), words[0][block.w], n)])


def _learn(held: DataFrame, n: int, v: int, rounds: int) -> np.ndarray:
    """Mixture weights per context bucket; the last row is of all contexts together."""
    weights = np.tile([0.5, 0.3, 0.2], (CONTEXT_BUCKETS + 1, 1))
    for _ in range(rounds):
        def expect(batches: Iterator[pa.RecordBatch], weights: np.ndarray = weights) -> Iterator[pa.RecordBatch]:
            total = np.zeros((CONTEXT_BUCKETS + 1, 3))
            for batch in batches:
                for row in batch.to_pylist():
                    pair, context, word, times = (_open(x).astype(np.float64) for x in pickle.loads(row["data"]))
                    p = np.stack([*_estimates(pair, context, word, n, v)])
                    k = _bucket(context)
                    for index in (k, np.full(len(k), CONTEXT_BUCKETS)):
                        share = weights[index].T * p
                        share *= times / share.sum(axis=0)
                        for i in range(3):
                            total[:, i] += np.bincount(index, weights=share[i], minlength=CONTEXT_BUCKETS + 1)
            yield pa.RecordBatch.from_arrays([pa.array(range(CONTEXT_BUCKETS + 1), pa.int32()), *[pa.array(total[:, i]) for i in range(3)]], ["k", "a", "b", "c"])

        sums = held.mapInArrow(expect, "k int, a double, b double, c double").groupBy("k").agg(*[F.sum(x).alias(x) for x in "abc"]).collect()  # 41 rows
        new = weights.copy()
        for r in sums:
            if (whole := r["a"] + r["b"] + r["c"]) > 0:
                new[r["k"]] = np.array([r["a"], r["b"], r["c"]]) / whole
        seen = {r["k"] for r in sums if r["a"] + r["b"] + r["c"] > 0}
        for k in set(range(CONTEXT_BUCKETS)) - seen:
            new[k] = new[CONTEXT_BUCKETS]
        if np.abs(new - weights).max() < 1e-4:
            return new
        weights = new
    return weights


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def scores(docs: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every document row."""
    spark = docs.sparkSession
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions", "200")), size // TASK_BYTES + 1)
    bits = max(1, (max(2 * parts, size // RANGE_BYTES) - 1).bit_length())
    gathered = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_gather(bits), ROW)
    routed = gathered.withColumn("route", F.when(F.col("kind") == 0, F.xxhash64("block")).otherwise(F.xxhash64("bucket"))).repartition(parts, "route").sortWithinPartitions("route", "kind", "bucket")
    summed = routed.mapInArrow(_add_up, ROW)
    blocks = persisted(summed.repartition(parts, "block").sortWithinPartitions("block").mapInArrow(_assemble, ROW))
    totals = [0, 0, 0, 0]
    for r in blocks.where("kind = 3").select("data").collect():  # four numbers per range of hashes
        totals = [x + y for x, y in zip(totals, pickle.loads(r["data"]))]
    weights = _learn(persisted(blocks.where("kind = 4")), totals[0], totals[1], rounds)
    weights[0, 0] = 0  # a context never seen has no bigrams
    weights[0] = weights[0] / weights[0].sum() if weights[0].sum() > 0 else [0, 0, 1]
    n, v = totals[2], totals[3]

    def price(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                if row["kind"] != 0:
                    continue
                block, told, words, pairs = _read(row["data"])
                word, pair = words[0] + words[1], pairs[0] + pairs[1]
                context = _context(word, block)
                bucket, log = _bucket(context), np.zeros(len(pair))
                for i, p in enumerate(_estimates(pair, context, word[block.w], n, v)):
                    log += weights[bucket, i] * p
                np.log10(log, out=log)
                base = np.log10((word + 0.1) / (n + 0.1 * (v + 1)))
                docs_, size = block.of_doc, len(block.lengths)
                sums = lambda x: np.bincount(docs_, weights=x, minlength=size)
                yield pa.RecordBatch.from_arrays([
                    pa.array(told["ids"], pa.int64()), pa.array(block.folds == HELD_OUT), pa.array(block.lengths.astype(np.int64)),
                    pa.array(sums((word > 0)[block.codes].astype(float)).astype(np.int64)), pa.array(np.full(size, n, np.int64)),
                    pa.array(sums(base[block.codes])), pa.array(sums(log[block.pair_of]))],
                    ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return blocks.mapInArrow(price, SCORES)
