"""SimHash near-duplicates found through Golay-code fuzzy hashing.

A 64-bit fingerprint is cut into three segments of at most 23 bits, each a word of the perfect
binary Golay code's space. Such a word has one codeword within three errors; the codewords of
the words within one error of it - one, or six when it has three errors itself - are its keys.
Two words at distance 2 or less share a key, for some word lies within one error of both; and if
they differ in one bit at most, the codeword of either is among the keys of the other.

Of four differing bits dealt to three segments, two segments get two together at most. So linked
fingerprints either agree in one segment and share a key of another, or differ in at most one bit
in each of two: then the pair (codeword of one's first, codeword of the other's second) is made by
both. Each fingerprint writes some sixty keys; rows of a key are brought together, and within a
key every pair that can be new is verified by its bits.

Within a key that many fingerprints share, the search walks from linked to linked fingerprint and
compares each only with those not yet reached: a dense group costs its size, not its square.
Keys beyond `group_rows` are dealt to blocks that meet pairwise, so no task holds all of one.

Copies are folded to one fingerprint before any of this. Defined results: null and empty texts
have fingerprint zero and link like any other; repeated rows each get their row.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.llm.common import persisted

SHINGLE, DISTANCE, SEED = 4, 4, 42
#: (lowest bit, width) of the three segments.
SEGMENTS = ((0, 22), (22, 21), (43, 21))
#: Generator polynomial of the Golay code (degree 11), a fixed value.
GENERATOR = 0b110001110101
GROUP_ROWS = 1_000_000


# ---- fingerprints ----------------------------------------------------------------------------

def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = ends - lengths
    n = max(1, len(words) - shingle + 1)
    first, last = starts[:n].tolist(), ends[len(words) - n:].tolist()
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter([digest(line[a:b], SEED) for a, b in zip(first, last)], np.uint64, n)
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 4096):  # bounded memory for any length
        ones += np.unpackbits(hashes[at:at + 4096].view(np.uint8), bitorder="little").reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int(sum(1 << int(i) for i in np.flatnonzero(2 * ones > n)))


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, *strings: str) -> DataFrame:
    """doc_id, fp (the fingerprint as a signed long), and the named string columns."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = np.fromiter((fingerprint(t.as_py(), shingle) for t in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got.view(np.int64)), *batch.columns[2:]], ["doc_id", "fp", *strings])

    return docs.select(F.col("doc_id").cast("long"), "text", *strings).mapInArrow(run, ", ".join(["doc_id long, fp long", *(f"{c} string" for c in strings)]))


# ---- Golay keys ------------------------------------------------------------------------------

def _remainders(words: np.ndarray) -> np.ndarray:
    """words modulo the generator, over GF(2)."""
    r = words.astype(np.int64).copy()
    for bit in range(22, 10, -1):
        r ^= np.where((r >> bit) & 1, GENERATOR << (bit - 11), 0)
    return r


@lru_cache(maxsize=1)
def _tables() -> tuple[np.ndarray, np.ndarray]:
    """By remainder (2048 rows): the error of weight three or less, and what to add to a word for each of its keys (-1: none)."""
    bits = 1 << np.arange(23, dtype=np.int64)
    a, b, c = np.meshgrid(np.r_[0, bits], np.r_[0, bits], np.r_[0, bits], indexing="ij")
    errors = np.unique((a | b | c).ravel())
    error = np.zeros(2048, np.int64)
    error[_remainders(errors)] = errors
    keys = np.full((2048, 6), -1, np.int64)
    for r in range(2048):
        own = error[r]
        # the codewords of all words at distance one, as differences from the word
        near = {int(own)} | {int(bit ^ error[r ^ int(_remainders(np.array([bit]))[0])]) for bit in bits}
        keys[r, :len(near)] = sorted(near)
    return error, keys


def codewords(words: np.ndarray) -> np.ndarray:
    """The information bits (12) of each word's codeword."""
    return (words ^ _tables()[0][_remainders(words)]) >> 11


def near_codewords(words: np.ndarray) -> np.ndarray:
    """Six columns of key indices per word; -1 where there are fewer."""
    add = _tables()[1][_remainders(words)]
    return np.where(add < 0, -1, (words[:, None] ^ np.maximum(add, 0)) >> 11)


def fuzzy_keys(fps: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (key, fingerprint) of all keys; keys of different kinds never meet."""
    parts = [(fps >> np.uint64(low)).astype(np.int64) & ((1 << width) - 1) for low, width in SEGMENTS]
    own, near = [codewords(p) for p in parts], [near_codewords(p) for p in parts]
    kind = 0

    def rows(head: np.ndarray, tail: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        keep = tail >= 0
        keys = (np.int64(kind) << np.int64(40)) | (head[:, None] << np.int64(12)) | np.maximum(tail, 0)
        return keys[keep], np.broadcast_to(fps[:, None], tail.shape)[keep]

    for i in range(3):
        for j in range(3):
            if i != j:  # agree in i, two bits at most in j
                kind += 1
                yield rows(parts[i], near[j])
    for i, j in ((0, 1), (0, 2), (1, 2)):  # one bit at most in each
        kind += 1
        yield rows(own[i], near[j])
        keep = near[i] >= 0
        keys = (np.int64(kind) << np.int64(40)) | (np.maximum(near[i], 0) << np.int64(12)) | own[j][:, None]
        yield keys[keep], np.broadcast_to(fps[:, None], near[i].shape)[keep]


def _keyed(distinct: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for at in range(0, len(fps), 4096):
                for keys, own in fuzzy_keys(fps[at:at + 4096]):
                    yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.ascontiguousarray(own).view(np.int64))], ["key", "fp"])

    return distinct.mapInArrow(run, "key long, fp long")


# ---- verified links --------------------------------------------------------------------------

def _reach(fps: np.ndarray, distance: int) -> list[tuple[int, int]]:
    """A spanning forest of the links among fps: each is compared only with those not yet reached."""
    edges: list[tuple[int, int]] = []
    rest = fps
    while len(rest) > 1:
        queue, rest = [rest[0]], rest[1:]
        while queue and len(rest):
            at = queue.pop()
            close = np.bitwise_count(rest ^ at) <= distance
            if close.any():
                got = rest[close]
                edges += [(int(at), int(x)) for x in got]
                queue += list(got)
                rest = rest[~close]
    return edges


class _Forest:
    """Keeps from a task's links only those that join two groups of it."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        up = self.up
        while (y := up.setdefault(x, x)) != x:
            up[x] = x = up.setdefault(y, y)
        return x

    def joins(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def _links(keyed: DataFrame, distance: int) -> DataFrame:
    """Verified links (a, b), a forest per batch, from rows sorted by key."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, fps = np.empty(0, np.int64), np.empty(0, np.uint64)
        for batch in batches:
            keys = np.r_[keys, batch.column(0).to_numpy(zero_copy_only=False)]
            fps = np.r_[fps, batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)]
            whole = int(np.searchsorted(keys, keys[-1])) if len(keys) else 0  # the last key may go on
            yield from out(keys[:whole], fps[:whole])
            keys, fps = keys[whole:], fps[whole:]
        yield from out(keys, fps)

    def out(keys: np.ndarray, fps: np.ndarray) -> Iterator[pa.RecordBatch]:
        if len(keys) < 2:
            return
        edges: list[tuple[int, int]] = []
        begins = np.r_[0, np.flatnonzero(np.diff(keys)) + 1]
        sizes = np.diff(np.r_[begins, len(keys)])
        few = np.repeat(sizes <= 8, sizes)
        for step in range(1, 8):
            if step >= len(keys):
                break
            pair = (keys[step:] == keys[:-step]) & few[step:]
            pair &= np.bitwise_count(fps[step:] ^ fps[:-step]) <= distance
            pair &= fps[step:] != fps[:-step]
            at = np.flatnonzero(pair)
            edges += zip(fps[at].tolist(), fps[at + step].tolist())
        for begin, size in zip(begins[sizes > 8].tolist(), sizes[sizes > 8].tolist()):
            edges += _reach(np.unique(fps[begin:begin + size]), distance)
        forest = _Forest()
        kept = [(a, b) for a, b in edges if forest.joins(a, b)]
        if kept:
            got = np.array(kept, np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(got[:, 0]), pa.array(got[:, 1])], ["a", "b"])

    return keyed.mapInArrow(run, "a long, b long")


def links(distinct: DataFrame, distance: int = DISTANCE, group_rows: int = GROUP_ROWS) -> DataFrame:
    """Links among distinct fingerprints that connect all that are within `distance`; a, b signed longs."""
    if distance > 4:
        raise ValueError("three Golay segments find up to 4 differing bits")
    parts = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))
    distinct = persisted(distinct.repartition(parts, "fp"))  # sixty times as many keys want as many tasks as there are
    keyed, rows = _keyed(distinct), distinct.count()
    if rows > group_rows:  # only then can a key hold more: deal its fingerprints to blocks that meet pairwise
        sizes = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > group_rows)
        blocks = sizes.select("key", F.ceil(2 * F.col("n") / group_rows).alias("blocks"))
        joined = keyed.join(F.broadcast(blocks) if blocks.limit(100_001).count() <= 100_000 else blocks, "key", "left")
        mine = F.pmod(F.xxhash64("fp"), F.coalesce("blocks", F.lit(1)))
        # block i meets block j in cell (min, max)
        cells = F.when(F.col("blocks").isNull(), F.array(F.lit(0).cast("long"))).otherwise(
            F.transform(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1), lambda j: F.least(mine, j) * F.col("blocks") + F.greatest(mine, j)))
        keyed = joined.select(F.explode(cells).alias("cell"), "key", "fp").select(F.when(F.col("cell") == 0, F.col("key")).otherwise(F.xxhash64("key", "cell").bitwiseOR(F.lit(1 << 62))).alias("key"), "fp")
    sorted_keys = keyed.repartition(parts, "key").sortWithinPartitions("key")
    return _links(sorted_keys, distance).distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root): the least node of each connected component, for nodes that have a link.

    Alternating stars: every node links its larger neighbours, then its smaller ones, to its least
    neighbour, until nothing changes; each round is cut by a reliable checkpoint.
    """
    now = persisted(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    before = None
    for _ in range(rounds):
        both = now.union(now.select("v", "u"))
        least = both.groupBy("u").agg(F.min("v").alias("m"))
        large = both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.least("m", "u").alias("v"))
        large = large.where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).distinct()
        now = persisted(small)
        state = now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        if state == before:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select(F.col("v"), F.col("v")).distinct())
        before = state
    raise RuntimeError(f"components did not settle in {rounds} rounds")


def _rooted(prints: DataFrame, distance: int) -> DataFrame:
    """fp, first, root: each distinct fingerprint with its least doc_id and the least fingerprint of its component."""
    firsts = prints.groupBy("fp").agg(F.min("doc_id").alias("first"))
    roots = components(links(firsts.select("fp"), distance))
    return firsts.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))


def classes(docs: DataFrame, shingle: int = SHINGLE, distance: int = DISTANCE) -> DataFrame:
    """doc_id, fp, component_id for every row; component_id is the least doc_id of its component."""
    prints = persisted(fingerprints(docs, shingle))
    tagged = _rooted(prints, distance)
    named = tagged.groupBy("root").agg(F.min("first").alias("component_id"))
    of_print = tagged.join(named, "root").select("fp", "component_id")
    return prints.join(of_print, "fp").select("doc_id", "fp", "component_id")


def representatives(docs: DataFrame, shingle: int = SHINGLE, distance: int = DISTANCE) -> DataFrame:
    """One document, all columns, of each near-duplicate class: the one of least doc_id, rows without one last.

    A row is told by its doc_id and its text's digest, so rows without an id and different texts of one id are
    rows of their own. Rows that repeat the first's doc_id and text are copies of it: one stays.
    """
    told = docs.withColumn("__sha", F.coalesce(F.sha2(F.col("text").cast("binary"), 256), F.lit("")))
    prints = persisted(fingerprints(told, shingle, "__sha"))
    of_print = prints.groupBy("fp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "__sha")).alias("row"))
    firsts = _rooted(prints, distance).join(of_print, "fp").groupBy("root").agg(F.min("row").alias("row"))
    firsts = firsts.select(F.col("row.doc_id").alias("__id"), F.col("row.__sha").alias("__of"))
    kept = told.join(firsts, (F.col("__sha") == F.col("__of")) & F.col("doc_id").cast("long").eqNullSafe(F.col("__id")))
    return kept.dropDuplicates(["doc_id", "__sha"]).drop("__sha", "__id", "__of")
