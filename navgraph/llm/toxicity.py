"""Toxicity by the nearest labelled examples.

Terms are words and their beginnings. The vocabulary is every term that several examples of a bounded sample of labelled
documents share, but for those that more than a twentieth of all documents have. A text is a vector of term counts times idf,
idf over all documents, of unit length. An inverted index over the examples keeps, per term and block of examples, the largest weight; that bounds
what a block can reach, blocks are scored from the most promising on, and those that can't change the k best are left out, so
the k nearest by cosine are exact. Votes weighted by closeness are made a probability with two numbers fitted on the examples
themselves, each left out of its own vote.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.llm.arrow import add_columns
from navgraph.llm.langid import held_out
from navgraph.llm.textscan import _BASE, _TABLE, LOWER, Words, _hashed, mix, powers, words
from navgraph.session import ship, written

LETTERS = np.zeros(256, bool)
LETTERS[[*range(0x61, 0x7B), *range(0x80, 0x100)]] = True
#: Characters of the beginnings that are terms of their own.
STEMS = (4, 6)
#: Labelled documents that are learned from, at most.
EXAMPLES = 4000
#: Examples that have a term of the vocabulary, at least; share of all documents that have it, at most (and so many documents in any case).
FEWEST, MOST_SHARE, MOST_ANYWAY = 2, 0.05, 20
NEIGHBOURS, BLOCK, SHRINK, THRESHOLD = 25, 256, 0.05, 0.3
#: Blocks that are scored first, and slices in which counts of the vocabulary come together.
PROMISING, SLICES = 2, 64
#: Queries that are searched together.
TOGETHER = 32


def terms(w: Words) -> tuple[np.ndarray, np.ndarray]:
    """Document (counted from w.first) and hash of every word, and of every beginning of a longer word."""
    doc = w.owner()
    sums = np.zeros(len(w.data) + 1, np.uint64)
    np.cumsum(_TABLE[LOWER][w.data] * powers(_BASE, len(w.data)), out=sums[1:])
    hashes, docs = [w.hashes], [doc]
    characters = np.append(np.flatnonzero((w.data & 0xC0) != 0x80), [len(w.data)] * max(STEMS) + [len(w.data)])
    at = np.searchsorted(characters, w.starts)
    for k, n in enumerate(STEMS):
        end = characters[np.minimum(at + n, len(characters) - 1)]
        long_ = end < w.ends
        hashes.append(mix(_hashed(sums[w.starts[long_]], sums[end[long_]], w.starts[long_], end[long_], _BASE) + np.uint64(k + 1)))
        docs.append(doc[long_])
    return np.concatenate(docs), np.concatenate(hashes)


def counted(doc: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (document, value), and how often each occurs."""
    order = np.lexsort((value, doc))
    doc, value = doc[order], value[order]
    first = np.flatnonzero(np.concatenate(([True], (doc[1:] != doc[:-1]) | (value[1:] != value[:-1])))) if len(doc) else np.zeros(0, np.int64)
    return doc[first], value[first], np.diff(np.append(first, len(doc)))


def counted_terms(doc: np.ndarray, term: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same for numbers of terms, sorted as one number."""
    key = np.sort(doc.astype(np.int64) << 32 | term)
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1]))) if len(key) else np.zeros(0, np.int64)
    return key[first] >> 32, key[first] & 0xFFFFFFFF, np.diff(np.append(first, len(key)))


class Vocabulary:
    def __init__(self, hashes: np.ndarray):
        self.hashes = np.sort(hashes)
        self.may = np.zeros(1 << 20, bool)
        self.may[(self.hashes & np.uint64((1 << 20) - 1)).astype(np.int64)] = True

    def find(self, doc: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Those (document, number of the term) that are in the vocabulary."""
        if not len(self.hashes):
            return doc[:0], np.zeros(0, np.int64)
        may = self.may[(hashes & np.uint64((1 << 20) - 1)).astype(np.int64)]
        doc, hashes = doc[may], hashes[may]
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        good = self.hashes[at] == hashes
        return doc[good], at[good]


def spread(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All places of the ranges start:end, and the range of each."""
    n = end - start
    which = np.repeat(np.arange(len(n)), n)
    return np.arange(len(which)) - np.repeat(np.cumsum(n) - n - start, n), which


class BlockMaxIndex:
    """Postings by term, in blocks of BLOCK examples, with the largest weight of each block."""

    def __init__(self, doc: np.ndarray, term: np.ndarray, weight: np.ndarray, n_docs: int, n_terms: int):
        order = np.lexsort((doc, term))
        self.doc, self.weight, self.n_docs = doc[order].astype(np.int32), weight[order].astype(np.float32), n_docs
        term = term[order]
        self.n_blocks = -(-n_docs // BLOCK)
        block = self.doc // BLOCK
        new = np.concatenate(([True], (block[1:] != block[:-1]) | (term[1:] != term[:-1]))) if len(block) else np.zeros(0, bool)
        self.start = np.flatnonzero(new).astype(np.int32)
        self.end = np.append(self.start[1:], len(self.doc))[: len(self.start)].astype(np.int32)
        self.block = block[self.start]
        self.most = np.maximum.reduceat(self.weight, self.start) if len(self.start) else self.weight
        self.block_at = np.searchsorted(self.start, np.searchsorted(term, np.arange(n_terms + 1))).astype(np.int32)

    def search(self, row: np.ndarray, term: np.ndarray, weight: np.ndarray, rows: int, k: int, leave: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        """For each of `rows` queries, given by row, term and weight: the k examples of the largest inner products over 0 (ties:
        the smaller number), without example leave[row]. Returns rows, examples and products, by row, then from the best on, and
        how many blocks were scored."""
        run, which = spread(self.block_at[term], self.block_at[term + 1])
        own, w = row[which], weight[which].astype(np.float32)
        cell = own * self.n_blocks + self.block[run]
        reach = np.bincount(cell, w * self.most[run], rows * self.n_blocks).reshape(rows, self.n_blocks)
        scores, least = np.zeros(rows * self.n_docs), np.zeros((rows, 1))

        def add(blocks: np.ndarray) -> None:
            some = np.flatnonzero(blocks.ravel()[cell])
            at, of = spread(self.start[run[some]], self.end[run[some]])
            of = some[of]
            scores[:] += np.bincount(own[of] * self.n_docs + self.doc[at], w[of] * self.weight[at], rows * self.n_docs)
            table = scores.reshape(rows, self.n_docs)
            if leave is not None:
                table[np.arange(rows), leave] = 0
            if self.n_docs > k:
                least[:, 0] = np.partition(table, self.n_docs - k, axis=1)[:, self.n_docs - k]

        first = np.zeros((rows, self.n_blocks), bool)
        best = np.argpartition(-reach, min(PROMISING, self.n_blocks - 1), axis=1)[:, :PROMISING] if self.n_blocks else np.zeros((rows, 0), np.int64)
        np.put_along_axis(first, best, True, 1)
        first &= reach > 0
        add(first)
        rest = ~first & (reach > 0) & (reach >= least * (1 - 1e-5))
        if rest.any():
            add(rest)
        table = scores.reshape(rows, self.n_docs)
        r, ids = np.nonzero((table > 0) & (table >= least))
        order = np.lexsort((ids, -table[r, ids], r))
        r, ids = r[order], ids[order]
        place = np.arange(len(r)) - np.searchsorted(r, r)
        r, ids = r[place < k], ids[place < k]
        return r, ids, table[r, ids], int(first.sum() + rest.sum())


class Neighbours:
    """Everything that a score needs: vocabulary, idf, index, labels and ids of examples, calibration."""

    def __init__(self, vocabulary: Vocabulary, idf: np.ndarray, doc: np.ndarray, term: np.ndarray, tf: np.ndarray, toxic: np.ndarray, ids: np.ndarray):
        """doc, term, tf: the examples' counts, by document, then term; idf 0 leaves a term out."""
        self.vocabulary, self.idf = vocabulary, idf
        doc, term, tf = (x[idf[term] > 0] for x in (doc, term, tf))
        weight = self.weigh(doc, term, tf, len(toxic))
        # Examples with the same strongest term stand side by side, so that blocks are alike within.
        lead = np.full(len(toxic), len(idf))
        strong = np.lexsort((-weight, doc))
        first = strong[np.flatnonzero(np.concatenate(([True], doc[strong][1:] != doc[strong][:-1])))] if len(doc) else strong
        lead[doc[first]] = term[first]
        order = np.argsort(lead, kind="stable")
        place = np.empty(len(toxic), np.int64)
        place[order] = np.arange(len(toxic))
        self.toxic, self.ids = toxic[order].astype(float), ids[order]
        self.index = BlockMaxIndex(place[doc], term, weight, len(toxic), len(idf))
        self.prior = float((self.toxic.sum() + 0.5) / (len(toxic) + 5)) if len(toxic) else 0.0
        self.line = (1.0, 0.0)
        if len(doc):
            own = np.unique(doc)
            votes = np.concatenate([v for v, _ in self.votes(np.searchsorted(own, doc), term, weight, len(own), place[own])])
            self.line = fitted(votes, self.toxic[place[own]])

    @staticmethod
    def loaded(data: bytes) -> Neighbours:
        return pickle.loads(data)  # noqa: S301 made by learn()

    def weigh(self, doc: np.ndarray, term: np.ndarray, tf: np.ndarray, n: int) -> np.ndarray:
        """Count times idf, of unit length per document."""
        weight = tf * self.idf[term]
        return weight / np.sqrt(np.bincount(doc, weight * weight, n))[doc] if len(doc) else weight

    def votes(self, row: np.ndarray, term: np.ndarray, weight: np.ndarray, rows: int, leave: np.ndarray | None = None):
        """Of each query the share of toxic votes, weighted by closeness, and its nearest examples (numbers and cosines), some queries at a time.
        row ascends."""
        edges = np.searchsorted(row, np.arange(0, rows + TOGETHER, TOGETHER))
        for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False)):
            n = min(TOGETHER, rows - k * TOGETHER)
            r, ids, scores, _ = self.index.search(row[a:b] - k * TOGETHER, term[a:b], weight[a:b], n, NEIGHBOURS, None if leave is None else leave[k * TOGETHER : k * TOGETHER + n])
            w = np.minimum(scores, 1.0)
            share = (np.bincount(r, w * self.toxic[ids], n) + SHRINK * self.prior) / (np.bincount(r, w, n) + SHRINK)
            at = np.searchsorted(r, np.arange(n + 1))
            yield share, [(ids[x:y], scores[x:y]) for x, y in zip(at[:-1], at[1:], strict=True)]

    def calibrated(self, votes: np.ndarray) -> np.ndarray:
        a, b = self.line
        v = np.clip(votes, 1e-4, 1 - 1e-4)
        return 1 / (1 + np.exp(-(a * np.log(v / (1 - v)) + b)))


def fitted(votes: np.ndarray, truth: np.ndarray) -> tuple[float, float]:
    """Slope and shift of a logistic curve over the votes' log-odds, by Newton steps with a small pull to (1, 0)."""
    v = np.clip(votes, 1e-4, 1 - 1e-4)
    x = np.stack((np.log(v / (1 - v)), np.ones(len(v))), 1)
    line, start = np.array([1.0, 0.0]), np.array([1.0, 0.0])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ line, -30, 30)))
        grad = x.T @ (p - truth) + (line - start)
        hess = (x * (p * (1 - p))[:, None]).T @ x + np.eye(2)
        line = line - np.linalg.solve(hess, grad)
    return float(max(line[0], 0.05)), float(line[1])


def idf_of(df: np.ndarray, total: int) -> np.ndarray:
    """0 for terms of too many documents."""
    return np.where(df <= max(MOST_SHARE * total, MOST_ANYWAY), np.log((1 + total) / np.maximum(df, 1)), 0.0)


def learn(docs: DataFrame, labels: DataFrame, most: int = EXAMPLES) -> bytes:
    """docs: doc_id, text (all of them, for idf). labels: doc_id, toxic (only those to learn from; null ones are left out, of
    several for one doc_id the largest counts). At most `most` labelled documents are used, chosen by a hash; repeated texts
    among them count once, with the label of the least doc_id. Vocabulary and index are made by one task each, from these
    examples alone; the driver gets the index as bytes (for score(), or Neighbours.loaded()).
    """
    spark = docs.sparkSession
    ship(spark)
    labels = labels.select("doc_id", "toxic").filter("toxic IS NOT NULL AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    some = labels.orderBy(F.xxhash64("doc_id", F.lit(5)), "doc_id").limit(most)
    # At most `most` rows of two numbers are broadcast.
    found = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(some), "doc_id")
    found = found.groupBy("text").agg(F.min(F.struct("doc_id", "toxic")).alias("own")).select(F.col("own.doc_id").cast("long").alias("doc_id"), (F.col("own.toxic") == 1).cast("int").alias("toxic"), "text")

    def count(batches):
        for batch in batches:
            hashes, counts = [b""] * batch.num_rows, [b""] * batch.num_rows
            for w in words(batch.column(2), LETTERS, LOWER):
                doc, term, tf = counted(*terms(w))
                at = np.searchsorted(doc, np.arange(len(w.offsets)))
                for i in range(len(at) - 1):
                    hashes[w.first + i], counts[w.first + i] = term[at[i] : at[i + 1]].tobytes(), tf[at[i] : at[i + 1]].astype(np.int32).tobytes()
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(hashes, pa.binary()), pa.array(counts, pa.binary()), pa.array([0] * batch.num_rows, pa.int32())], names=["doc_id", "toxic", "terms", "counts", "all"])

    examples = written(found.mapInArrow(count, "doc_id long, toxic int, terms binary, counts binary, all int"), "toxicity-examples")

    def shared(key, table):
        own, n = np.unique(np.concatenate([np.frombuffer(x, np.uint64) for x in table.column("terms").to_pylist()]), return_counts=True)
        return pa.table({"terms": pa.array([own[n >= FEWEST].tobytes()], pa.binary())})

    made = examples.select("all", "terms").groupBy("all").applyInArrow(shared, "terms binary").collect()
    known = np.frombuffer(bytes(made[0]["terms"]), np.uint64) if made else np.zeros(0, np.uint64)
    sent = spark.sparkContext.broadcast(known.tobytes())
    edges = np.linspace(0, len(known), SLICES + 1).astype(np.int64)

    def frequencies(batches):
        have = Vocabulary(np.frombuffer(sent.value, np.uint64))
        df, n = np.zeros(len(have.hashes), np.int64), 0
        for batch in batches:
            n += batch.num_rows
            for w in words(batch.column(0), LETTERS, LOWER):
                df += np.bincount(counted_terms(*have.find(*terms(w)))[1], minlength=len(df))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(SLICES + 1), pa.int32()), pa.array([*(df[a:b].tobytes() for a, b in zip(edges, edges[1:], strict=False)), np.array([n]).tobytes()], pa.binary())], names=["slice", "counts"])

    def add(key, table):
        return pa.table({"slice": pa.array([key[0].as_py()], pa.int32()), "counts": pa.array([sum(np.frombuffer(x, np.int64) for x in table.column("counts").to_pylist()).tobytes()], pa.binary())})

    sums = docs.select("text").mapInArrow(frequencies, "slice int, counts binary").groupBy("slice").applyInArrow(add, "slice int, counts binary").collect()
    parts = {r["slice"]: np.frombuffer(bytes(r["counts"]), np.int64) for r in sums}
    sent.destroy()
    total = int(parts[SLICES][0]) if parts else 0
    idf = idf_of(np.concatenate([parts[k] for k in range(SLICES)]) if parts else np.zeros(len(known), np.int64), total)
    kept = known[idf > 0].copy(), idf[idf > 0].copy()

    def index(key, table):
        table = table.sort_by("doc_id")
        vocabulary = Vocabulary(kept[0])
        blobs = [np.frombuffer(x, np.uint64) for x in table.column("terms").to_pylist()]
        doc, hashes, tf = np.repeat(np.arange(len(blobs)), [len(x) for x in blobs]), np.concatenate(blobs), np.frombuffer(b"".join(table.column("counts").to_pylist()), np.int32)
        at = np.searchsorted(vocabulary.hashes, hashes)
        good = (at < len(vocabulary.hashes)) & (vocabulary.hashes[np.minimum(at, max(0, len(vocabulary.hashes) - 1))] == hashes) if len(vocabulary.hashes) else np.zeros(len(hashes), bool)
        model = Neighbours(vocabulary, kept[1], doc[good], at[good], tf[good].astype(np.int64), table.column("toxic").to_numpy(), table.column("doc_id").to_numpy())
        return pa.table({"model": pa.array([pickle.dumps(model)], pa.binary())})

    made = examples.groupBy("all").applyInArrow(index, "model binary").collect()
    none = np.zeros(0, np.int64)
    return bytes(made[0]["model"]) if made else pickle.dumps(Neighbours(Vocabulary(np.zeros(0, np.uint64)), np.zeros(0), none, none, none, none, none))


def score(docs: DataFrame, model: bytes) -> DataFrame:
    """Adds score (0 to 1), predicted (1 from THRESHOLD up) and evidence (nearest examples) to `docs`, which needs text.

    A text without any term of the vocabulary, an empty or a null one has no neighbour; its score is the share of toxic
    examples. Other columns stay, those of the three names are replaced. An empty table gives an empty result.
    """
    # A model's size is bounded by EXAMPLES documents' terms.
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        model = Neighbours.loaded(sent.value)

        def work(batch):
            n = batch.num_rows
            scores, evidence = np.full(n, model.prior), [[]] * n
            for w in words(batch.column(batch.schema.get_field_index("text")), LETTERS, LOWER):
                doc, term, tf = counted_terms(*model.vocabulary.find(*terms(w)))
                if not len(doc):
                    continue
                own, row = np.unique(doc, return_inverse=True)
                at = 0
                for votes, near in model.votes(row, term, model.weigh(row, term, tf, len(own)), len(own)):
                    some = w.first + own[at : at + len(votes)]
                    scores[some] = np.where([len(x) > 0 for x, _ in near], model.calibrated(votes), model.prior)
                    for i, (ids, cosines) in zip(some.tolist(), near, strict=True):
                        evidence[i] = [{"doc_id": d, "similarity": s, "toxic": t} for d, s, t in zip(model.ids[ids[:3]].tolist(), cosines[:3].tolist(), model.toxic[ids[:3]].astype(int).tolist(), strict=True)]
                    at += len(votes)
            return {"score": pa.array(scores), "predicted": pa.array((scores >= THRESHOLD).astype(np.int32)), "evidence": evidence}

        return work

    return add_columns(docs, "score double, predicted int, evidence array<struct<doc_id:long,similarity:double,toxic:int>>", make)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic").filter(~held_out("doc_id", 4, 2))
    model = learn(docs, labels)
    return score(docs.withColumn("held_out", held_out("doc_id", 4, 2)), model).select("doc_id", "held_out", "score", "predicted", "evidence")
