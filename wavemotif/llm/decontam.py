"""Benchmark decontamination by SimHash of item-sized windows.

Items are grouped into size classes (lengths a quarter apart). For an item of a class with length c, every window of c words in it
is fingerprinted; in documents, windows of c words at every STEP words of the text are, or at every word if an item of the class has
fewer than STEP windows. So one of the windows of an exact passage meets a window of the item wherever it stands. A fingerprint has 64 bits: the signs of sums of word
vectors, which running sums give for all windows of a text at once. Fingerprints of items are cut into radius + 1 blocks, each
with its own table: two fingerprints within the radius agree in a block at least, so looking up all blocks finds all of them, and
the Hamming distance decides. Each hit places an item in a text; there the weighted Jaccard similarity of the full sets of five-word
shingles of the item and of the item-sized window, tried at the place and a few words to both sides, decides. A shingle weighs
more the fewer items of the whole benchmark it occurs in; one aggregation counts them, and those in several items go to the executors.

The benchmark is read in blocks of BLOCK_ITEMS items and BLOCK_BYTES of text at most, each block a bounded table sent to the executors and run against all
documents; documents are never shuffled. Words: A-Z lower-cased, cut at ASCII white space, outer punctuation removed.

Defined cases: null or empty texts match nothing, nor do items without words; items of fewer words than a shingle are matched
whole; repeated items give one row each; repeated rows of documents give repeated rows. Items with null item_id are left out, and
documents with null doc_id are matched but never dropped, since no id names them.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavemotif.llm.common import WordHashes, Workspace, anti_by_id, documents, map_batches, mix64, shingle_hashes, utf8

RADIUS = 5
STEP = 2
RATIO = 1.25
SHINGLE = 5
BLOCK_ITEMS = 20_000
BLOCK_BYTES = 32 << 20
BATCH_WORDS = 16_384
TRIM = b"".join(bytes([c]) for c in range(33, 127) if not chr(c).isalnum())
SLIDE = (0, -1, 1, -2, 2, -3, 3)


def bare(word: bytes) -> bytes:
    return word.strip(TRIM) or word


def size_class(n: int) -> int:
    """The largest class length that leaves room for STEP offsets, if the item has them."""
    room = max(1, n - STEP + 1) if n > 4 else n
    c = 1
    while (nxt := max(c + 1, int(c * RATIO))) <= room:
        c = nxt
    return c


def word_signs(hashes: np.ndarray) -> np.ndarray:
    """+1 or -1 in 64 dimensions a word."""
    return np.unpackbits(mix64(hashes)[:, None].view(np.uint8), axis=1).astype(np.int16) * 2 - 1


def running(hashes: np.ndarray) -> np.ndarray:
    """Sums of the vectors of all words before each word, and of all of them; blocks of rows are added side by side."""
    n = len(hashes)
    out = np.zeros((-(-n // 64) * 64 + 1, 64), np.int32)
    out[1 : n + 1] = word_signs(hashes)
    rows = out[1:].reshape(-1, 64, 64)
    for i in range(1, 64):
        rows[:, i] += rows[:, i - 1]
    rows[1:] += np.cumsum(rows[:, -1], axis=0)[:-1, None]
    return out[: n + 1]


def fingerprints(sums: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    return np.packbits(sums[starts + length] > sums[starts], axis=1).view(np.uint64).ravel()


class BlockIndex:
    """All fingerprints within a radius, by tables over blocks of bits."""

    def __init__(self, prints: np.ndarray, radius: int):
        self.prints, self.radius = prints, radius
        edges = [round(64 * i / (radius + 1)) for i in range(radius + 2)]
        self.blocks = [(np.uint64(a), np.uint64((1 << (b - a)) - 1)) for a, b in zip(edges, edges[1:], strict=False)]
        self.tables = []
        for shift, mask in self.blocks:
            keys = ((prints >> shift) & mask).astype(np.int64)
            order = np.argsort(keys, kind="stable")
            ends = np.searchsorted(keys[order], np.arange(int(mask) + 2))
            self.tables.append((order, ends, ends[1:] > ends[:-1]))

    def near(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(query, print) numbers of all pairs within the radius, once each."""
        q, p = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for (shift, mask), (order, ends, held) in zip(self.blocks, self.tables, strict=True):
            key = ((queries >> shift) & mask).astype(np.int64)
            hit = np.flatnonzero(held[key])
            if not len(hit):
                continue
            lo = ends[key[hit]]
            n = ends[key[hit] + 1] - lo
            rep = np.repeat(hit, n)
            at = order[np.arange(len(rep)) + np.repeat(lo - np.cumsum(n) + n, n)]
            good = np.bitwise_count(queries[rep] ^ self.prints[at]) <= self.radius
            q.append(rep[good])
            p.append(at[good])
        pairs = np.unique(np.concatenate(q) * len(self.prints) + np.concatenate(p))  # one number a pair
        return pairs // len(self.prints), pairs % len(self.prints)


class Weights:
    """log(1 + n / c) of a shingle in c of the n items of a benchmark; only those in several items are held, the others weigh as c = 1."""

    def __init__(self, n: int, hashes: np.ndarray, counts: np.ndarray):
        order = np.argsort(hashes)
        self.hashes, self.shared, self.single = hashes[order], np.log(1 + n / counts[order]), math.log(1 + n)

    def of(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.hashes):
            return np.full(len(hashes), self.single)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return np.where(self.hashes[at] == hashes, self.shared[at], self.single)


class Benchmark:
    """A block of items: fingerprints of their windows by class, and their weighted shingles. Without weights the block is the benchmark."""

    def __init__(self, items: list[tuple[int, bytes]], radius: int = RADIUS, step: int = STEP, weights: Weights | None = None):
        self.step, hashes = step, WordHashes(bare)
        words = [(i, hashes.array(t.lower().split())) for i, t in items]
        self.ids = [i for i, w in words if len(w)]
        words = [(i, w) for i, w in words if len(w)]
        self.length = [len(w) for _, w in words]
        shingles = [np.unique(shingle_hashes(w, SHINGLE)) for _, w in words]
        self.weights = weights or Weights(len(words), *np.unique(np.concatenate([np.empty(0, np.uint64), *shingles]), return_counts=True))
        self.shingles = [dict(zip(s.tolist(), self.weights.of(s).tolist(), strict=True)) for s in shingles]
        self.total = [sum(s.values()) for s in self.shingles]
        by: dict[int, list[tuple[int, int, np.ndarray]]] = {}
        for k, (_, w) in enumerate(words):
            c = size_class(len(w))
            starts = np.arange(len(w) - c + 1)
            by.setdefault(c, []).append((k, len(starts), fingerprints(running(w), starts, c)))
        self.classes = {}
        for c, parts in by.items():
            item = np.repeat([k for k, _, _ in parts], [m for _, m, _ in parts])
            offset = np.concatenate([np.arange(m) for _, m, _ in parts])
            every = step if min(m for _, m, _ in parts) >= step else 1
            self.classes[c] = (BlockIndex(np.concatenate([f for _, _, f in parts]), radius), item, offset, every)

    def similarity(self, words: np.ndarray, start: int, item: int) -> float:
        """Weighted Jaccard of the item and the item-sized window at start."""
        window = words[max(0, start) : max(0, start + self.length[item])]
        if not len(window):
            return 0.0
        want, both, others = self.shingles[item], 0.0, []
        for h in set(shingle_hashes(window, SHINGLE).tolist()):
            if h in want:
                both += want[h]
            else:
                others.append(h)
        extra = float(self.weights.of(np.array(others, np.uint64)).sum()) if others else 0.0
        return both / (self.total[item] + extra)

    def matches(self, texts: list[np.ndarray], least: float) -> list[dict[int, tuple[float, int]]]:
        """For each text, item number to (best similarity, word at which its window starts). Texts are fingerprinted together."""
        found: list[dict[int, tuple[float, int]]] = [{} for _ in texts]
        if not any(map(len, texts)):
            return found
        # texts begin at multiples of the step, so what is found in one does not depend on those before it
        sums = running(np.concatenate([np.pad(t, (0, -len(t) % self.step)) for t in texts]))
        begins = np.cumsum([0] + [-(-len(t) // self.step) * self.step for t in texts[:-1]])
        ends = begins + [len(t) for t in texts]
        for c, (index, item, offset, step) in self.classes.items():
            if len(sums) <= c:
                continue
            starts = np.arange(0, len(sums) - c, step)
            of = np.searchsorted(begins, starts, "right") - 1
            q, p = index.near(np.packbits(sums[c::step][: len(starts)] > sums[: len(starts) * step : step], axis=1).view(np.uint64).ravel())
            inside = starts[q] + c <= ends[of[q]]  # a window across two texts is none
            q, p = q[inside], p[inside]
            places = set(zip(of[q].tolist(), item[p].tolist(), (starts[q] - begins[of[q]] - offset[p]).tolist(), strict=True))
            for doc, k, start in sorted(places):
                for slide in SLIDE:
                    if (s := self.similarity(texts[doc], start + slide, k)) >= least and s > found[doc].get(k, (0.0, 0))[0]:
                        found[doc][k] = (s, start + slide)
                    if s == 1.0:
                        break
        return found


def batches_of(texts: list[np.ndarray], words: int = BATCH_WORDS) -> Iterator[list[np.ndarray]]:
    """Consecutive texts with about so many words together."""
    part, n = [], 0
    for t in texts:
        part.append(t)
        n += len(t)
        if n >= words:
            yield part
            part, n = [], 0
    yield part


def _items(benchmark: DataFrame) -> DataFrame:
    return benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).where("item_id is not null and text is not null")


def benchmark_weights(benchmark: DataFrame) -> Weights:
    """Shingle weights over all items; the driver gets the shingles that several items hold."""

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        hashes = WordHashes(bare)
        sets = [np.unique(shingle_hashes(hashes.array(t.lower().split()), SHINGLE)).view(np.int64) for t in utf8(batch)]
        return pa.RecordBatch.from_arrays([pa.array([s for s in sets if len(s)], pa.list_(pa.int64()))], ["shingles"])

    sets = map_batches(_items(benchmark), fn, "shingles array<long>")
    shared = sets.select(F.explode("shingles").alias("h")).groupBy("h").agg(F.count("*").alias("c")).where("c > 1").toArrow()
    return Weights(sets.count(), shared.column("h").to_numpy().view(np.uint64), shared.column("c").to_numpy())


def item_blocks(benchmark: DataFrame, size: int = BLOCK_ITEMS, limit: int = BLOCK_BYTES) -> Iterator[list[tuple[int, bytes]]]:
    """Items in blocks of a bounded number and bounded bytes (a longer item is alone); only one block is on the driver at a time."""
    block: list[tuple[int, bytes]] = []
    held = 0
    for item, text in _items(benchmark).toLocalIterator():
        raw = text.encode()
        if block and (len(block) == size or held + len(raw) > limit):
            yield block
            block, held = [], 0
        block.append((item, raw))
        held += len(raw)
    yield block


def contaminated(docs: DataFrame, benchmark: DataFrame, least: float = 0.8, radius: int = RADIUS, step: int = STEP) -> DataFrame:
    """doc_id, item_id, similarity, start_word a row a document and an item that it holds."""
    out, context = None, docs.sparkSession.sparkContext
    weights = context.broadcast(benchmark_weights(benchmark))
    for block in item_blocks(benchmark):
        shared = context.broadcast(block)

        def run(shared=shared):
            made, hashes = None, WordHashes(bare)

            def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
                nonlocal made
                made = made or Benchmark(shared.value, radius, step, weights.value)
                rows = []
                every = [f for part in batches_of([hashes.array(t.lower().split()) for t in utf8(batch)]) for f in made.matches(part, least)]
                for doc, found in zip(batch.column("doc_id").to_pylist(), every, strict=True):
                    rows += [(doc, made.ids[k], round(s, 6), a) for k, (s, a) in sorted(found.items())]
                cols = list(zip(*rows, strict=True)) or [()] * 4
                kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64())
                return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "item_id", "similarity", "start_word"])

            return fn

        part = map_batches(documents(docs), run(), "doc_id long, item_id long, similarity double, start_word long")
        out = part if out is None else out.unionByName(part)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, least: float = 0.8) -> DataFrame:
    """docs without those that hold an item; columns unchanged."""
    return anti_by_id(docs, contaminated(docs, benchmark, least), Workspace(docs.sparkSession))
