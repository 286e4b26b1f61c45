"""Language-model scoring with a log-frequency Bloom filter of n-gram counts.

An n-gram of count c has level 1 + floor(log(c) / log(STEP)) and is put into the filter once for each level up to its own; a
count is read back by asking level after level until one is absent. The filter holds all word pairs of the training
documents, those seen once as well. It has one segment per hash bucket, as large as the bucket's pairs need, so it grows with
the corpus; no process holds more than one segment. The counts of words are exact, and so is the base score.

Documents are dealt into chunks. A chunk tells each bucket its distinct words and pairs with their numbers in training
documents; the bucket, which hears all chunks, adds up, makes its segment and answers with counts and levels in the order of asking, and
the chunk's documents meet the answers: an n-gram goes over the network once per chunk.

The model: p(w | v) = max(c(vw) - D, 0) / c(v) + l * p1(w), with counts rounded to levels, p1 the base's formula on them, the
discount D = n1 / (n1 + 2 n2), 0.9 at most, from the numbers of pairs seen once and twice, and l by size of c(v): the share that discounting
sets free there. The discount is what tells a text that the corpus holds once, itself, from one that it holds again. A token's share
depends only on its three levels, so a table of how many tokens have which levels says as much as the tokens themselves.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.llm.arrow import fresh, named
from navgraph.llm.deal import deal_of, firsts, mask, packed, totals, unpack
from navgraph.llm.langid import held_out
from navgraph.llm.textscan import GRAPHIC, LOWER, Words, mix, steps, words
from navgraph.session import ship, written

#: WAYS bits an entry; FIRST_WAYS for the levels of counts 1 and 2, as most pairs that are asked for were seen never or once.
STEP, WAYS, FIRST_WAYS = math.sqrt(2), 3, 8
#: Share of set bits of the filter, and classes of c(v).
LOAD, CLASSES = 0.35, 12
#: Bytes of a hash that are sent: of a word all, of a pair so many below its bucket's bits.
WORD, PAIR = 8, 5
ADD = 0.1
#: Where hardly a pair is seen twice, one seen once still counts for something.
MOST_DISCOUNT = 0.9
END, BEGIN = np.uint64(0x3C5A9D1E7F208B46), np.uint64(0x71E2C8A4D63B05F9)
LEVELS = 128
#: Stands in for the level of END and BEGIN, whose count is the number of documents.
ENDS = LEVELS


def level(counts: np.ndarray) -> np.ndarray:
    return 1 + np.floor(np.log(np.maximum(counts, 1)) / math.log(STEP) + 1e-9).astype(np.int64)


#: What a level stands for: the middle of the counts that have it. No count has level 2; it counts as level 1.
_low = np.ceil(STEP ** (np.arange(LEVELS, dtype=float) - 1) - 1e-6)
MEANS = np.where(np.arange(LEVELS) == 0, 0.0, (_low + np.maximum(_low, np.ceil(STEP ** np.arange(LEVELS, dtype=float) - 1e-6) - 1)) / 2)
MEANS[2] = 1.0
#: Levels that counts have.
USED = (1, *range(3, LEVELS))
TWICE = int(level(np.array([2]))[0])


def tokens(w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash of each token and of the one before it, and its document counted from w.first; each document ends with END."""
    n = len(w.offsets) - 1
    doc = np.repeat(np.arange(n), w.counts + 1)
    own = np.empty(len(doc), np.uint64)
    last = w.offsets[1:] + np.arange(n)
    inner = np.ones(len(doc), bool)
    inner[last] = False
    own[inner], own[last] = w.hashes, END
    before = np.empty_like(own)
    before[1:] = own[:-1]
    before[w.offsets[:-1] + np.arange(n)] = BEGIN
    return own, before, doc


def pair(before: np.ndarray, own: np.ndarray) -> np.ndarray:
    return mix(before * np.uint64(0xA0761D6478BD642F) + own)


class Segment:
    """The filter of one bucket's pairs."""

    def __init__(self, data: np.ndarray):
        self.data, self.bits = data, len(data) * 8

    @staticmethod
    def ways(q: int) -> int:
        return FIRST_WAYS if q <= TWICE else WAYS

    @classmethod
    def of(cls, hashes: np.ndarray, levels: np.ndarray) -> Segment:
        entries = [(q, hashes[levels >= q]) for q in USED if q <= levels.max(initial=0)]
        need = sum(len(h) * cls.ways(q) for q, h in entries) / -math.log(1 - LOAD)
        made = cls(np.zeros(max(8, math.ceil(need / 8)), np.uint8))
        own = np.zeros(made.bits, bool)
        for q, h in entries:
            for at in made.places(h, q):
                own[at] = True
        made.data = np.packbits(own, bitorder="little")
        return made

    def places(self, hashes: np.ndarray, q: int):
        x = mix(hashes ^ np.uint64((q * 0x9E3779B97F4A7C15 + 0x5851F42D4C957F2D) & 0xFFFFFFFFFFFFFFFF))
        step = mix(x ^ np.uint64(0xD1B54A32D192ED03)) | np.uint64(1)
        for _ in range(self.ways(q)):
            yield (x % np.uint64(self.bits)).astype(np.int64)
            x = x + step

    def read(self, hashes: np.ndarray) -> np.ndarray:
        """Levels as the filter has them: one after another until one is absent."""
        found, left = np.zeros(len(hashes), np.uint8), np.arange(len(hashes))
        for q in USED:
            if not len(left):
                break
            has = np.ones(len(left), bool)
            for at in self.places(hashes[left], q):
                has &= (self.data[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
            left = left[has]
            found[left] = q
        return found


class Model:
    """Totals of the training documents, and what follows from levels."""

    def __init__(self, total: int, distinct: int, documents: int):
        self.total, self.distinct, self.documents = total, distinct, documents
        self.discount, self.freed = 0.5, np.ones(CLASSES)

    def parts(self, before: np.ndarray, own: np.ndarray, both: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """From levels: p1 of a token, the counts of its pair and of the one before, and the class of that one."""
        value = np.append(MEANS, float(self.documents))
        c_before = np.maximum(value[before], 1)
        p1 = (value[own] + ADD) / (self.total + ADD * (self.distinct + 1))
        return p1, value[both], c_before, np.minimum(np.log2(c_before).astype(np.int64) // 2, CLASSES - 1)

    def fit(self, cells: np.ndarray, n: np.ndarray) -> None:
        """Discount and freed shares from how many training tokens (n) have which levels (cells, as cell() makes them)."""
        _, c2, _, kind = self.parts(cells >> 16, cells >> 8 & 255, cells & 255)
        pairs = n / np.maximum(c2, 1)  # each distinct pair stands in as many tokens as its count
        once, twice = (float(pairs[(cells & 255) == q].sum()) for q in (1, TWICE))
        self.discount = min(once / (once + 2 * twice), MOST_DISCOUNT) if once else 0.5
        tokens = np.bincount(kind, n, CLASSES)
        self.freed = np.where(tokens > 0, self.discount * np.bincount(kind, pairs, CLASSES) / np.maximum(tokens, 1), 1.0)

    def log10(self, cells: np.ndarray) -> np.ndarray:
        """log10 probability of tokens with these levels."""
        p1, c2, c_before, kind = self.parts(cells >> 16, cells >> 8 & 255, cells & 255)
        return np.log10(np.minimum(np.maximum(c2 - self.discount, 0) / c_before, 1.0) + self.freed[kind] * p1)


def cell(n: np.ndarray, own: pa.Array, both: pa.Array) -> np.ndarray:
    """Levels of the token before, the token and the pair of both in one number, for documents of n tokens each."""
    own, both = (np.frombuffer(b"".join(x.to_pylist()), np.uint8).astype(np.int64) for x in (own, both))
    before = np.empty_like(own)
    before[1:] = own[:-1]
    before[np.cumsum(n) - n] = ENDS
    return before << 16 | own << 8 | both


def small(batches, at: int):
    """Batches cut to about 2^18 tokens, whose numbers are in column `at`."""
    for batch in batches:
        for i, j in steps(np.append(0, np.cumsum(batch.column(at).to_numpy())), 1 << 18):
            yield batch.slice(i, j - i)


def numbered(hashes: np.ndarray, learned: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes, ascending, and how often each is learned."""
    order = np.argsort(hashes)
    own = hashes[order]
    first = firsts(own)
    return own[first], np.add.reduceat(learned[order].astype(np.int64), first) if len(first) else np.zeros(0, np.int64)


def score(docs: DataFrame, train: str = "train") -> DataFrame:
    """Adds n_tokens, n_known, train_tokens, base_score and score to `docs`, which needs text and a boolean column `train`
    that says which rows are learned from (null: not). All columns stay (those of the five names are replaced), all rows are
    scored; they must be of types that Spark can hash.

    Null texts count as empty: one token, the end. With nothing to learn from, every token has the probability 1 / (V + 1)
    for an empty V. Rows are told apart by 128 bits of hash of all their columns; repeated rows share theirs, and their sums
    are divided by their number. An empty table gives an empty result.
    """
    spark = docs.sparkSession
    ship(spark)
    names = ("n_tokens", "n_known", "train_tokens", "base_score", "score")
    keep = [named(c) for c in docs.columns if c.lower() not in names]
    one, two = fresh([*docs.columns, *names], "row_hash", "row_salted")
    marked = docs.select(*keep, F.xxhash64(*keep).alias(one), F.xxhash64(F.lit(1), *keep).alias(two))
    deal = deal_of(docs)
    bits, cut = deal.bits, mask(deal.bits, PAIR)
    dealt = marked.select(named("text").alias("text"), F.col(one).alias("one"), F.col(two).alias("two"), F.coalesce(named(train), F.lit(False)).alias("learned")).withColumn("chunk", deal.chunk("one"))

    def read(table):
        """Of every step: tokens, their pairs, document and whether it is learned from; and the number of documents."""
        learned = table.column("learned").to_numpy()
        for w in words(table.column("text"), GRAPHIC, LOWER):
            own, before, doc = tokens(w)
            yield own, pair(before, own) & cut, doc, learned[w.first + doc], len(w.offsets) - 1

    def ask(key, table):
        found = list(read(table))
        learned = np.concatenate([f[3] for f in found])
        sent = [dict(zip(*packed(*numbered(np.concatenate([f[k] for f in found]), learned), bits, width), strict=True)) for k, width in ((0, WORD), (1, PAIR))]
        buckets = sorted({*sent[0], *sent[1]})
        return pa.table({"bucket": pa.array(buckets, pa.int32()), "chunk": pa.array([key[0].as_py()] * len(buckets), pa.int32()), "words": pa.array([sent[0].get(b) for b in buckets], pa.binary()), "pairs": pa.array([sent[1].get(b) for b in buckets], pa.binary())})

    def answer(key, table):
        b, none = key[0].as_py(), np.zeros(2, np.uint32).tobytes()
        x, y = ([unpack(blob or none, b, bits, width) for blob in table.column(c).to_pylist()] for c, width in (("words", WORD), ("pairs", PAIR)))
        _, c, place = totals(x)
        counts = np.split(c[place], np.cumsum([len(h) for h, _ in x])[:-1])
        h, n, place = totals(y)
        segment = Segment.of(h[n > 0], level(n[n > 0]))
        levels = np.split(segment.read(h)[place], np.cumsum([len(k) for k, _ in y])[:-1])
        # One more row, to chunk -1: the number of distinct words learned in this bucket.
        return pa.table({"chunk": pa.array([*table.column("chunk").to_pylist(), -1], pa.int32()), "bucket": pa.array([b] * (len(x) + 1), pa.int32()), "counts": pa.array([*(k.astype(np.int64).tobytes() for k in counts), np.array([(c > 0).sum()], np.int64).tobytes()], pa.binary()), "levels": pa.array([*(k.tobytes() for k in levels), b""], pa.binary())})

    def measure(key, table, answers):
        answers = answers.sort_by("bucket")
        counts = np.frombuffer(b"".join(answers.column("counts").to_pylist()), np.int64)
        levels = np.frombuffer(b"".join(answers.column("levels").to_pylist()), np.uint8)
        out: dict[str, list] = {k: [] for k in ("n_tokens", "n_known", "base", "own", "both")}
        if not len(table):  # chunk -1
            null = pa.nulls(1, pa.int64())
            return pa.table({"one": null, "two": null, "learned": pa.nulls(1, pa.bool_()), "n_tokens": null, "n_known": pa.array([int(counts.sum())]), "base": pa.nulls(1, pa.float64()), "own": pa.nulls(1, pa.binary()), "both": pa.nulls(1, pa.binary())})
        found = list(read(table))
        for k, answered in ((0, counts), (1, levels)):
            hashes = np.concatenate([f[k] for f in found])
            order = np.argsort(hashes)
            own = hashes[order]
            of = np.empty(len(hashes), answered.dtype)
            of[order] = answered[np.cumsum(np.concatenate(([0], own[1:] != own[:-1])))]
            found = [(*f, o) for f, o in zip(found, np.split(of, np.cumsum([len(f[0]) for f in found])[:-1]), strict=True)]
        for own, _, doc, _, n, c, both in found:
            of_own = np.where(own == END, ENDS, np.where(c > 0, level(c), 0)).astype(np.uint8)
            ends = np.cumsum(np.bincount(doc, minlength=n))
            out["n_tokens"].append(np.diff(ends, prepend=0))
            out["n_known"].append(np.bincount(doc, c > 0, n).astype(np.int64))
            out["base"].append(np.bincount(doc, np.log10(c + ADD), n))
            for name, x in (("own", of_own.tobytes()), ("both", both.tobytes())):
                out[name] += [x[i:j] for i, j in zip(np.append(0, ends[:-1]), ends, strict=True)]
        return pa.table({"one": table.column("one"), "two": table.column("two"), "learned": table.column("learned"), **{k: np.concatenate(out[k]) for k in ("n_tokens", "n_known", "base")}, "own": pa.array(out["own"], pa.binary()), "both": pa.array(out["both"], pa.binary())})

    def tally(batches):
        for batch in small(batches, 0):
            cells, n = np.unique(cell(batch.column(0).to_numpy(), *batch.columns[1:]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(n)], names=["cell", "n"])

    asked = dealt.groupBy("chunk").applyInArrow(ask, "bucket int, chunk int, words binary, pairs binary")
    answers = asked.groupBy("bucket").applyInArrow(answer, "chunk int, bucket int, counts binary, levels binary")
    measured = dealt.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(measure, "one long, two long, learned boolean, n_tokens long, n_known long, base double, own binary, both binary")
    measured = written(measured, "lm-levels")
    own = F.col("one").isNotNull()
    known = measured.agg(F.sum(F.when(F.col("learned"), F.col("n_tokens"))), F.sum(F.when(~own, F.col("n_known"))), F.count(F.when(F.col("learned"), 1))).first()
    total, distinct, documents = (int(x or 0) for x in known)
    model = Model(total, distinct, documents)
    cells = measured.filter("learned").select("n_tokens", "own", "both").mapInArrow(tally, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    model.fit(cells.column("cell").to_numpy(), cells.column("n").to_numpy())
    log_all = math.log10(total + ADD * (distinct + 1))

    def log10(batches):
        for batch in small(batches, 2):
            n = batch.column(2).to_numpy()
            sums = np.bincount(np.repeat(np.arange(len(n)), n), model.log10(cell(n, *batch.columns[5:])), len(n))
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sums, pa.float64())], names=["one", "two", "n_tokens", "n_known", "base", "score"])

    sums = (
        measured.filter(own).select("one", "two", "n_tokens", "n_known", "base", "own", "both").mapInArrow(log10, "one long, two long, n_tokens long, n_known long, base double, score double")
        .groupBy(F.col("one").alias(f"{one}_"), F.col("two").alias(f"{two}_")).agg(*(F.avg(x).alias(x) for x in ("n_tokens", "n_known", "base", "score")))
    )
    sums = sums.select(f"{one}_", f"{two}_", F.col("n_tokens").cast("long").alias("n_tokens"), F.col("n_known").cast("long").alias("n_known"), F.lit(total).cast("long").alias("train_tokens"), (F.col("base") - F.col("n_tokens") * F.lit(log_all)).alias("base_score"), "score")
    return marked.join(sums, (F.col(one) == F.col(f"{one}_")) & (F.col(two) == F.col(f"{two}_"))).select(*keep, *names)


def op5_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").withColumn("held_out", held_out("doc_id", 10, 0)).withColumn("train", ~F.col("held_out"))
    return score(docs).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score")
