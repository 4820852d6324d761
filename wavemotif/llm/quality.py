"""Quality of documents by an interpolated modified Kneser-Ney n-gram model of trusted text.

The model reads words letter by letter: an n-gram is up to five symbols of a word framed by start marks and an end mark, and a
word equal to the one before it is a symbol of its own. Each digit and letter of any script is told apart; those beyond U+07BF are
two symbols. Symbols take 12 bits, so an n-gram is an integer and contexts and suffixes are shifts and masks; counting, continuation counts, discounts and interpolation are DataFrame
aggregations and joins over all trusted text. Tasks sum words and then n-grams before anything is shuffled.

Scoring is a join of the n-grams that the corpus holds with the count tables, dealt by n-gram: each asks for its
probabilities and back-off weights of all orders at once, and the answers give its log probability. A task sends each n-gram it meets
once, so what is joined grows with the n-grams of the corpus and not with its symbols. The scored n-grams are sent to the executors up
to BROADCAST_GRAMS (64 MB), where a document is a sum over its words; beyond that the counted n-grams of each document meet them in
a salted join. The model itself never leaves its tables.

The perplexity of a document is taken per symbol. In each language the threshold is a quantile of the perplexities of all its
trusted documents; a language without trusted text gets the quantile over all of them.

Defined cases: documents without words have no perplexity and are kept; without trusted text all are kept; null lang is
a language of its own; several labels of a document must all be good; null labels do not count.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavemotif.llm.common import SLICE_ROWS, Workspace, anti_by_id, documents, map_batches, measured, semi_by_id, utf8

ORDER = 5
BITS = 12
START, END, SAME = 1, 2, 3
MASK = (1 << BITS) - 1
#: Largest number of scored n-grams (16 bytes each) that is sent to the executors; beyond it texts meet them by a join.
BROADCAST_GRAMS = 4_000_000
SALTS = 32
FLUSH_WORDS = 200_000
KNOWN_WORDS = 400_000
#: Stands for a word that equals the one before; no valid UTF-8.
REPEAT = b"\xff"
#: First of the lead and of the trail symbols of letters that take two: 1984 + 1088 + 1024 symbols fill the 12 bits.
LEAD, TRAIL = np.uint64(1984), np.uint64(3072)
MARKS = {m: chr(0xD800 + m) for m in (START, END, SAME)}
QUANTILE = 0.995


def symbols(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(codes, lengths): for each word START marks, its letters, END; length counts letters and END.

    No two letters share a symbol: code points below LEAD are one, the others, and those with the numbers of the marks, are a lead
    (their upper bits) and a trail (the lower ten). The marks are lone surrogates until then, which no text holds."""
    text = "".join(MARKS[START] * (ORDER - 1) + (MARKS[SAME] if w == REPEAT else w.decode("utf-8", "replace")) + MARKS[END] for w in words)
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    mark = (code > 0xD800) & (code <= 0xD800 + SAME)
    long = ((code >= LEAD) | ((code >= START) & (code <= SAME))) & ~mark
    code[mark] -= np.uint64(0xD800)
    if long.any():
        first = np.cumsum(1 + long) - 1 - long
        wide = np.empty(len(code) + int(long.sum()), np.uint64)
        wide[first] = np.where(long, LEAD + (code >> np.uint64(10)), code)
        wide[first[long] + 1] = TRAIL + (code[long] & np.uint64(1023))
        code = wide
    ends = np.flatnonzero(code == END)
    return code, np.diff(np.concatenate([[-1], ends])) - (ORDER - 1)


def grams(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(keys of all n-grams of the words, word number of each)."""
    code, n = symbols(words)
    key = np.zeros(len(code), np.uint64)
    for back in range(ORDER):
        key[back:] |= code[: len(code) - back] << np.uint64(BITS * back)
    own = np.concatenate([np.arange(a + ORDER - 1, b) for a, b in _bounds(n)]) if len(words) < 64 else np.flatnonzero(_inside(n))
    return key[own], np.repeat(np.arange(len(words)), n)


def _bounds(n: np.ndarray) -> list[tuple[int, int]]:
    ends = np.cumsum(n + ORDER - 1)
    return list(zip((ends - n - ORDER + 1).tolist(), ends.tolist(), strict=True))


def _inside(n: np.ndarray) -> np.ndarray:
    mark = np.ones(int((n + ORDER - 1).sum()), bool)
    starts = np.cumsum(n + ORDER - 1) - n - (ORDER - 1)
    mark[(starts[:, None] + np.arange(ORDER - 1)).ravel()] = False
    return mark


def repeats(words: list[bytes]) -> list[bytes]:
    """Words with each that equals the one before replaced by the repeat symbol."""
    return [REPEAT if a == b else a for a, b in zip(words, [b"", *words], strict=False)]


# ---------------------------------------------------------------- the model
def count_grams(docs: DataFrame) -> DataFrame:
    """(key, c): partial counts of the n-grams of all texts, summed within each task."""

    def run(batches):
        words: Counter = Counter()

        def flush():
            if words:
                key, of = grams(list(words))
                uniq, at = np.unique(key, return_inverse=True)
                c = np.bincount(at, weights=np.fromiter(words.values(), np.float64, len(words))[of])
                words.clear()
                yield pa.RecordBatch.from_arrays([pa.array(uniq.astype(np.int64)), pa.array(c.astype(np.int64))], ["key", "c"])

        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                for text in utf8(batch.slice(at, SLICE_ROWS)):
                    words.update(repeats(text.split()))
                if len(words) > FLUSH_WORDS:
                    yield from flush()
        yield from flush()

    return documents(docs).select("text").mapInArrow(run, "key long, c long")


def save_counts(counts: DataFrame, ws: Workspace, name: str) -> DataFrame:
    return ws.save(counts, name, **{f"n{i}": F.count_if(F.col("c") == i) for i in (1, 2, 3, 4)})


def discounts(counts: DataFrame) -> tuple[float, float, float]:
    """Of counts 1, 2 and 3 or more, from the numbers of n-grams that occur one to four times, as measured by save_counts."""
    n1, n2, n3, n4 = (measured(counts, f"n{i}") for i in (1, 2, 3, 4))
    if not n1 or not n2:
        return 0.5, 0.5, 0.5
    y = n1 / (n1 + 2 * n2)
    return tuple(float(min(max(d, 0.05), k - 0.05)) for k, d in ((1, 1 - 2 * y * n2 / n1), (2, 2 - 3 * y * n3 / n2), (3, 3 - 4 * y * (n4 / n3 if n3 else 0))))


def kneser_ney(counts: DataFrame, ws: Workspace) -> tuple[DataFrame, int]:
    """((tag, key, value), number of symbols and one for those never seen): tag k = 1 .. ORDER has log p of seen n-grams of k symbols, tag 8 + k log weights of backing off from contexts of k symbols.

    The highest order uses counts, lower ones the number of different symbols that an n-gram follows.
    """
    levels = {ORDER: counts}
    for k in range(ORDER - 1, 0, -1):
        levels[k] = save_counts(levels[k + 1].groupBy(F.col("key").bitwiseAND((1 << (BITS * k)) - 1).alias("key")).agg(F.count("*").alias("c")), ws, f"level{k}")
    size = measured(levels[1]) + 1
    below, out = None, []
    for k in range(1, ORDER + 1):
        d1, d2, d3 = discounts(levels[k])
        d = F.when(F.col("c") == 1, d1).when(F.col("c") == 2, d2).otherwise(d3)
        rows = levels[k].select("key", "c", F.shiftright("key", BITS).alias("ctx"), d.alias("d"))
        ctx = rows.groupBy("ctx").agg(F.sum("c").alias("total"), (F.sum("d") / F.sum("c")).alias("gamma"))
        rows = rows.join(ctx, "ctx").withColumn("own", (F.col("c") - F.col("d")) / F.col("total"))
        if below is None:
            rows = rows.select("key", (F.col("own") + F.col("gamma") / size).alias("p"))
        else:
            low = below.select(F.col("key").alias("suffix"), F.col("p").alias("q"))
            rows = rows.withColumn("suffix", F.col("key").bitwiseAND((1 << (BITS * (k - 1))) - 1)).join(low, "suffix").select("key", (F.col("own") + F.col("gamma") * F.col("q")).alias("p"))
        below = ws.save(rows, f"p{k}")
        out += [below.select(F.lit(k).alias("tag"), "key", F.log("p").alias("value")), ctx.select(F.lit(8 + k - 1).alias("tag"), F.col("ctx").alias("key"), F.log("gamma").alias("value"))]
    spread = out[0]
    for part in out[1:]:
        spread = spread.unionByName(part)
    return spread, size


def needed_grams(docs: DataFrame) -> DataFrame:
    """key: the n-grams of ORDER symbols that occur in the texts, once each; a task sends each of its own once a flush."""

    def run(batches):
        words: set[bytes] = set()

        def flush():
            if words:
                keys = np.unique(grams(list(words))[0])
                words.clear()
                yield pa.RecordBatch.from_arrays([pa.array(keys.astype(np.int64))], ["key"])

        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                for text in utf8(batch.slice(at, SLICE_ROWS)):
                    words.update(repeats(text.split()))
                if len(words) > FLUSH_WORDS:
                    yield from flush()
        yield from flush()

    return documents(docs).select("text").mapInArrow(run, "key long").distinct()


def score_grams(needed: DataFrame, model: DataFrame, size: int) -> DataFrame:
    """key, lp: the log probability of the last symbol of each needed n-gram.

    One join on (tag, key) with the model, both sides dealt by that key: an n-gram asks for the probabilities of its suffixes and
    the back-off weights of their contexts; the answers meet again by n-gram.
    """
    suffix = lambda k: F.col("gram").bitwiseAND((1 << (BITS * k)) - 1)
    asked = [F.struct(F.lit(k).alias("tag"), suffix(k).alias("key")) for k in range(1, ORDER + 1)]
    asked += [F.struct(F.lit(8 + k - 1).alias("tag"), F.shiftright(suffix(k), BITS).alias("key")) for k in range(1, ORDER + 1)]
    rows = needed.select(F.col("key").alias("gram")).select("gram", F.explode(F.array(*asked)).alias("a")).select("gram", "a.tag", "a.key")
    found = rows.join(model, ["tag", "key"], "left").groupBy("gram").agg(*[F.max(F.when(F.col("tag") == t, F.col("value"))).alias(f"v{t}") for t in (*range(1, ORDER + 1), *range(8, 8 + ORDER))])
    lp = F.coalesce(F.col("v8"), F.lit(0.0)) - float(np.log(size))  # a symbol never seen
    for k in range(1, ORDER + 1):
        lp = F.coalesce(F.col(f"v{k}"), lp + (F.coalesce(F.col(f"v{8 + k - 1}"), F.lit(0.0)) if k > 1 else F.lit(0.0)))
    return found.select(F.col("gram").alias("key"), lp.alias("lp"))


def scores_beside_words(docs: DataFrame, scored: DataFrame) -> DataFrame:
    """doc_id, lang, n_words, lp, symbols a row of docs, from the scores of all its n-grams in one table on every executor."""
    table = scored.toArrow()
    key, lp = table["key"].to_numpy(), table["lp"].to_numpy()
    order = np.argsort(key)
    shared = scored.sparkSession.sparkContext.broadcast((key[order].astype(np.uint64), lp[order]))
    known: dict[bytes, int] = {}
    sums, n = np.empty(0), np.empty(0, np.int64)

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        nonlocal sums, n
        texts = [repeats(t.split()) for t in utf8(batch)]
        if len(known) > KNOWN_WORDS:
            known.clear()
            sums, n = np.empty(0), np.empty(0, np.int64)
        new = list({w for t in texts for w in t if w not in known})
        if new:
            keys, values = shared.value
            own, of = grams(new)
            known.update(zip(new, range(len(sums), len(sums) + len(new)), strict=True))
            sums = np.concatenate([sums, np.bincount(of, weights=values[np.searchsorted(keys, own)], minlength=len(new))])
            n = np.concatenate([n, np.bincount(of, minlength=len(new))])
        at = [np.fromiter(map(known.__getitem__, t), np.int64, len(t)) for t in texts]
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("lang"), pa.array(list(map(len, texts)), pa.int64()), pa.array([float(sums[i].sum()) for i in at], pa.float64()), pa.array([int(n[i].sum()) for i in at], pa.int64())], ["doc_id", "lang", "n_words", "lp", "symbols"])

    return map_batches(docs, fn, "doc_id long, lang string, n_words long, lp double, symbols long")


def scores_by_join(docs: DataFrame, scored: DataFrame) -> DataFrame:
    """The same rows where the scores are too many to be sent: the n-grams of each text, counted, meet their scores by key.

    Frequent n-grams occur in most texts, so a key is dealt in SALTS parts.
    """

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for text in utf8(batch):
            words = repeats(text.split())
            key, c = np.unique(grams(words)[0], return_counts=True) if words else (np.empty(0, np.uint64), np.empty(0, np.int64))
            rows.append((len(words), key.astype(np.int64), c))
        ends = pa.array(np.cumsum([0, *[len(k) for _, k, _ in rows]]), pa.int32())
        lists = [pa.ListArray.from_arrays(ends, pa.array(np.concatenate([np.empty(0, np.int64), *[r[i] for r in rows]]).astype(np.int64))) for i in (1, 2)]
        return pa.RecordBatch.from_arrays([batch.column("row"), batch.column("doc_id"), batch.column("lang"), pa.array([m for m, _, _ in rows], pa.int64()), *lists], ["row", "doc_id", "lang", "n_words", "keys", "counts"])

    counted = Workspace(docs.sparkSession).save(map_batches(docs.withColumn("row", F.monotonically_increasing_id()), fn, "row long, doc_id long, lang string, n_words long, keys array<long>, counts array<long>"), "counted")
    parts = counted.select("row", F.explode(F.arrays_zip("keys", "counts")).alias("g")).select("row", F.col("g.keys").alias("key"), F.col("g.counts").alias("c"), F.pmod(F.xxhash64("row"), F.lit(SALTS)).cast("int").alias("salt"))
    salted = scored.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    sums = parts.join(salted, ["key", "salt"]).groupBy("row").agg(F.sum(F.col("c") * F.col("lp")).alias("lp"), F.sum("c").alias("symbols"))
    return counted.drop("keys", "counts").join(sums, "row", "left").select("doc_id", "lang", "n_words", F.coalesce("lp", F.lit(0.0)).alias("lp"), F.coalesce("symbols", F.lit(0)).alias("symbols"))


def perplexities(docs: DataFrame, scored: DataFrame, limit: int = BROADCAST_GRAMS) -> DataFrame:
    """doc_id, lang, n_words, perplexity a row of docs, from a saved scored(key, lp), which has every n-gram of docs."""
    rows = documents(docs, "lang").withColumn("lang", F.col("lang").cast("string"))
    rows = scores_beside_words(rows, scored) if measured(scored) <= limit else scores_by_join(rows, scored)
    return rows.select("doc_id", "lang", "n_words", F.when(F.col("symbols") > 0, F.exp(-F.col("lp") / F.col("symbols"))).alias("perplexity"))


# ---------------------------------------------------------------- the classifier
def classify(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """doc_id, lang, n_words, perplexity, threshold, kept a row of docs."""
    ws = Workspace(docs.sparkSession)
    good = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("q")).where("q = 1").select("doc_id")
    good = ws.save(good, "trusted")
    n = measured(good)
    counts = save_counts(count_grams(semi_by_id(docs.withColumn("doc_id", F.col("doc_id").cast("long")), good, n)).groupBy("key").agg(F.sum("c").alias("c")), ws, "counts")
    if not measured(counts):
        words = F.regexp_count(F.coalesce(F.col("text"), F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")
        return documents(docs, "lang").select("doc_id", F.col("lang").cast("string").alias("lang"), words.alias("n_words"), F.lit(None).cast("double").alias("perplexity"), F.lit(None).cast("double").alias("threshold"), F.lit(True).alias("kept"))
    model, size = kneser_ney(counts, ws)
    scored = ws.save(score_grams(needed_grams(docs), model, size), "scores")
    scored = ws.save(perplexities(docs, scored), "scored")
    trusted = semi_by_id(scored.where("perplexity is not null"), good, n)
    per = trusted.groupBy(F.col("lang").alias("of")).agg(F.percentile_approx("perplexity", quantile, 100_000).alias("own"))
    whole = trusted.agg(F.percentile_approx("perplexity", quantile, 100_000).alias("all"))
    limits = F.coalesce("own", "all")
    out = scored.join(per, F.col("lang").eqNullSafe(F.col("of")), "left").crossJoin(F.broadcast(whole))  # one row
    return out.select("doc_id", "lang", "n_words", "perplexity", limits.alias("threshold"), F.coalesce(F.col("perplexity") <= limits, F.lit(True)).alias("kept"))


def keep_quality(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """docs without the documents that the classifier rejects; columns unchanged."""
    return anti_by_id(docs, classify(docs, labels, quantile).where("not kept"), Workspace(docs.sparkSession))
