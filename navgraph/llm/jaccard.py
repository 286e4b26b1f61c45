"""Jaccard join of documents on word shingles, by signature trees.

1. Chunks of documents ask buckets of shingle hashes how often each shingle occurs. That gives its class (once, 2 or more, 8,
   64, 512 or more times). A document of which less than the threshold's share occurs more than once links with nothing.
2. Documents with equal sets are one node. Nodes that share one of their rarest shingles (so many that linked sets can't miss
   each other) fall into one block, found as connected components.
3. In a block a signature tree is built: a node holds the OR of its sets' bitmaps and the range of their sizes. It is joined
   with itself from the top; node pairs whose possible overlap is too small are left out, and pairs of leaves that remain are
   compared exactly, all sets of one with all of the other. A large block is cut into pieces by content, and every pair of
   pieces is joined in a task of its own.
4. A task gives how many documents each of its sets links with, and as many links as join them into components; no list of all
   pairs is made. Components of the links give the answer.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.llm.arrow import fresh, named
from navgraph.llm.components import components, united
from navgraph.llm.deal import counted, cuts, deal_of, firsts, mask, packed, totals, unpack
from navgraph.llm.textscan import GRAPHIC, LOWER, Words, words
from navgraph.session import ship, written

SHINGLE, PERCENT = 5, 75
#: Least number of occurrences of each class of shingles.
CLASSES = np.array([2, 8, 64, 512])
#: Bytes of a hash below its bucket's bits that the census keeps: a class needs no more.
WIDTH = 4
#: Nodes of a piece, pieces of a block by content, and shingles of a piece (a block of more is cut further by hash).
PIECE, PIECES, PIECE_SHINGLES = 128, 32, 1 << 21
#: Sets of a leaf, most shingles of a leaf of several sets, and children of a node.
LEAF, LEAF_SHINGLES, FANOUT = 16, 200_000, 8
#: Bits of a bitmap per shared shingle of a leaf: so many that unlike leaves have few bits in common.
SPARSE = 16


#: The lowest bits of a shingle's hash are left clear, for its class.
_CLEAR = ~np.uint64(7)


def shingles(w: Words, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles, document by document, repeats included, and where each document's begin, and the end."""
    runs, few = np.maximum(w.counts - size + 1, 0), np.flatnonzero((w.counts > 0) & (w.counts < size))
    runs[few] = 1
    ends = np.cumsum(runs)
    hashes, long_ = np.empty(int(ends[-1]) if len(ends) else 0, np.uint64), np.ones(int(ends[-1]) if len(ends) else 0, bool)
    long_[ends[few] - 1] = False
    hashes[long_] = w.grams(size)[1]
    hashes[~long_] = w.spans(w.offsets[few], w.offsets[few + 1])
    return hashes & _CLEAR, np.concatenate(([0], ends))


def distinct(values: np.ndarray) -> np.ndarray:
    """Like np.unique, with less ado."""
    if len(values) < 2:
        return values
    values = np.sort(values)
    return values[np.concatenate(([True], values[1:] != values[:-1]))]


class Block:
    """Sets that are joined with each other: sizes, and of each set the numbers of those shingles that several sets have."""

    def __init__(self, sets: list[np.ndarray]):
        self.size = np.array([len(s) for s in sets])
        owner = np.repeat(np.arange(len(sets)), self.size)
        uni, number, n = np.unique(np.concatenate(sets) if len(sets) else np.zeros(0, np.uint64), return_inverse=True, return_counts=True)
        several = n[number] > 1
        renumbered = np.cumsum(n > 1) - 1
        self.column, self.n_columns = renumbered[number[several]], int((n > 1).sum())
        self.at = np.searchsorted(owner[several], np.arange(len(sets) + 1))

    def rows(self, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row (place in `which`) and column of every shared shingle of these sets."""
        n = self.at[which + 1] - self.at[which]
        return np.repeat(np.arange(len(which)), n), self.column[np.repeat(self.at[which] - np.cumsum(n) + n, n) + np.arange(n.sum())]

    def linked(self, a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
        """Which sets of a link with which of b: overlaps by one matrix product over the shingles that both sides have."""
        (ra, ca), (rb, cb) = self.rows(a), self.rows(b)
        there = np.zeros(self.n_columns, np.int8)
        there[ca] = 1
        there[cb] |= 2
        both = np.flatnonzero(there == 3)
        number = np.zeros(self.n_columns, np.int64)
        number[both] = np.arange(len(both))
        x, y = np.zeros((len(a), len(both)), np.float32), np.zeros((len(b), len(both)), np.float32)
        inside = there[ca] == 3
        x[ra[inside], number[ca[inside]]] = 1
        inside = there[cb] == 3
        y[rb[inside], number[cb[inside]]] = 1
        overlap = np.rint(x @ y.T).astype(np.int64)
        return 100 * overlap >= percent * (self.size[a][:, None] + self.size[b][None, :] - overlap)


class SignatureTree:
    """Leaves of neighbouring sets (in the order given), nodes of FANOUT children. Per node: OR of bitmaps, least and largest
    size, and most shingles of one of its sets that share a bit with another of the same set (so that the overlap of two
    sets is at most their nodes' common bits plus the smaller of these numbers)."""

    def __init__(self, block: Block, order: np.ndarray):
        """order: the sets of `block` that the tree is made of."""
        self.block, edges, held = block, [0], 0
        shared = (block.at[1:] - block.at[:-1])[order]
        for k, n in enumerate(shared.tolist()):
            held += n
            if k > edges[-1] and (k - edges[-1] >= LEAF or held > LEAF_SHINGLES):
                edges.append(k)
                held = n
        self.first, self.leaves = np.array(edges), np.split(order, edges[1:])
        self.order, self.shared = order, shared
        self.most = int(np.add.reduceat(shared, self.first).max())

    def mark(self, bits: int) -> None:
        """Makes the bitmaps, of `bits` bits (a power of two)."""
        rows, own = self.block.rows(self.order)
        place = ((own.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)) & np.uint64(bits - 1)
        taken = distinct(rows.astype(np.uint64) << np.uint64(24) | place)
        spare = self.shared - np.bincount((taken >> np.uint64(24)).astype(np.int64), minlength=len(self.order))
        marks = np.zeros((len(self.first), bits // 64), np.uint64)
        leaf = np.searchsorted(self.first, rows, "right") - 1
        np.bitwise_or.at(marks, (leaf, (place >> np.uint64(6)).astype(np.int64)), np.uint64(1) << (place & np.uint64(63)))
        size = self.block.size[self.order]
        self.levels = [(marks, *(f.reduceat(x, self.first) for f, x in ((np.minimum, size), (np.maximum, size), (np.maximum, spare))))]
        while len(self.levels[-1][1]) > 1:
            first = np.arange(0, len(self.levels[-1][1]), FANOUT)
            self.levels.append(tuple(f.reduceat(x, first) for f, x in zip((np.bitwise_or, np.minimum, np.maximum, np.maximum), self.levels[-1], strict=True)))

    def possible(self, level: int, a: np.ndarray, other: SignatureTree, b: np.ndarray, percent: int) -> np.ndarray:
        """Whether sets below nodes a and b (pairwise) may link: sizes near enough, and the largest possible overlap enough."""
        m, lo, hi, s = self.levels[level]
        m2, lo2, hi2, s2 = other.levels[level]
        near = (100 * hi[a] >= percent * lo2[b]) & (100 * hi2[b] >= percent * lo[a])
        overlap = np.minimum(np.bitwise_count(m[a] & m2[b]).sum(1, dtype=np.int64) + np.minimum(s[a], s2[b]), np.minimum(hi[a], hi2[b]))
        return near & (100 * overlap >= percent * (lo[a] + lo2[b] - overlap))


def tree_join(sets: list[np.ndarray], left: list[int], right: list[int], percent: int, copies: np.ndarray | None = None) -> tuple[list[tuple[int, int]], np.ndarray, int]:
    """Joins the sets of `left` with those of `right` (equal lists: within). Sets are ascending and not empty.

    Returns links that connect what all links connect, per set the copies (default: one each) it links with, and the number of pairs that
    were compared. Goes down two trees together, level by level.
    """
    copies = np.ones(len(sets), np.int64) if copies is None else copies
    partners, links, compared = np.zeros(len(sets), np.int64), [], 0
    self_join = left == right
    if not left or not right or (self_join and len(left) < 2):
        return links, partners, compared
    block = Block(sets)
    # Sets of like size stand side by side; of those, sets with the same least shared shingle.
    like = np.floor(np.log(block.size) / np.log(100 / percent))
    lead = np.array([block.column[block.at[i]] if block.at[i + 1] > block.at[i] else -1 for i in range(len(sets))])
    trees = [SignatureTree(block, own[np.lexsort((lead[own], like[own]))]) for own in (np.array(left), np.array(right))[: 1 if self_join else 2]]
    bits = 1 << min(17, max(6, (SPARSE * max(t.most for t in trees)).bit_length()))
    for t in trees:
        t.mark(bits)
    trees = trees * 2 if self_join else trees
    up = list(range(len(sets)))

    def root(i: int) -> int:
        while up[i] != i:
            up[i] = i = up[up[i]]
        return i

    top = min(len(trees[0].levels), len(trees[1].levels)) - 1
    a, b = (x.ravel() for x in np.indices([len(t.levels[top][1]) for t in trees]))
    for level in range(top, -1, -1):
        if self_join:
            a, b = a[a <= b], b[a <= b]
        good = np.concatenate([trees[0].possible(level, a[k : k + 2048], trees[1], b[k : k + 2048], percent) for k in range(0, len(a), 2048)] or [np.zeros(0, bool)])
        a, b = a[good], b[good]
        if level:
            n = [len(t.levels[level - 1][1]) for t in trees]
            a, b = (np.repeat(a * FANOUT, FANOUT**2) + np.tile(np.repeat(np.arange(FANOUT), FANOUT), len(a)), np.repeat(b * FANOUT, FANOUT**2) + np.tile(np.arange(FANOUT), FANOUT * len(b)))
            inside = (a < n[0]) & (b < n[1])
            a, b = a[inside], b[inside]
    for i, j in zip(a.tolist(), b.tolist(), strict=True):
        p, q = trees[0].leaves[i], trees[1].leaves[j]
        compared += len(p) * len(q)
        found = block.linked(p, q, percent)
        if self_join and i == j:
            np.fill_diagonal(found, False)
        if not found.any():
            continue
        partners[p] += found @ copies[q]
        if not (self_join and i == j):
            partners[q] += copies[p] @ found
        while True:
            rp, rq = np.array([root(x) for x in p]), np.array([root(x) for x in q])
            new = found & (rp[:, None] != rq[None, :])
            rows = np.flatnonzero(new.any(1))
            if not len(rows):
                break
            for r, c in zip(rows.tolist(), new[rows].argmax(1).tolist(), strict=True):
                x, y = root(p[r]), root(q[c])
                if x != y:
                    up[max(x, y)] = min(x, y)
                    links.append((int(p[r]), int(q[c])))
    return links, partners, compared


def near_groups(docs: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """One row (doc_id, n_shingles, component_id, n_links) per row of `docs`, which needs doc_id (whole numbers) and text.

    Sets are of distinct shingles of `size` words (A-Z lower-cased); fewer words make one shingle; no words, or null, none,
    which links with nothing. Sets link when their Jaccard similarity is at least percent / 100. component_id is the least
    doc_id reachable by links; n_links counts the other rows that a row's set links with, rows with an equal set among them.
    Rows that share a doc_id pool their groups. A row with a null doc_id links with nothing and has itself (null) as component.
    An empty table gives an empty result; other columns are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    numbered = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    deal = deal_of(docs)
    bits, cut = deal.bits, mask(deal.bits, WIDTH)
    dealt = numbered.withColumn("chunk", deal.chunk("id", "text"))

    def read(table):
        """Shingles of all texts and where each text's begin, and the end."""
        found, ends = [np.zeros(0, np.uint64)], [np.zeros(1, np.int64)]
        for w in words(table.column("text"), GRAPHIC, LOWER):
            hashes, at = shingles(w, size)
            found.append(hashes)
            ends.append(at[1:] + ends[-1][-1])
        return np.concatenate(found), np.concatenate(ends)

    def ask(key, table):
        hashes, counts = counted(read(table)[0] & cut)
        buckets, blobs = packed(hashes, counts, bits, WIDTH)
        return pa.table({"chunk": pa.array([key[0].as_py()] * len(blobs), pa.int32()), "bucket": pa.array(buckets, pa.int32()), "blob": pa.array(blobs, pa.binary())})

    def answer(key, table):
        b = key[0].as_py()
        parts = [unpack(x, b, bits, WIDTH) for x in table.column("blob").to_pylist()]
        _, n, place = totals(parts)
        kinds = np.searchsorted(CLASSES, n, "right").astype(np.uint8)[place]
        ends = np.cumsum([len(h) for h, _ in parts])
        return pa.table({"chunk": table.column("chunk"), "bucket": table.column("bucket"), "kinds": pa.array([x.tobytes() for x in np.split(kinds, ends[:-1])], pa.binary())})

    def measure(key, table, answers):
        kinds = np.frombuffer(b"".join(answers.sort_by("bucket").column("kinds").to_pylist()), np.uint8)
        hashes, at = read(table)
        order = np.argsort(hashes & cut)
        own = (hashes & cut)[order]
        if len(own):  # the answers are in the order of distinct hashes
            hashes[order] |= kinds[np.cumsum(np.concatenate(([0], own[1:] != own[:-1])))]
        ids, texts = table.column("id").combine_chunks(), table.column("text").combine_chunks()
        valid, rows = ids.is_valid().to_numpy(zero_copy_only=False), []
        for i in range(len(at) - 1):
            tokens = distinct(hashes[at[i] : at[i + 1]])
            kind, n = (tokens & ~_CLEAR).astype(np.uint8), len(tokens)
            shared = int(np.count_nonzero(kind))
            if n and valid[i] and 100 * shared >= percent * n:
                rare = tokens[np.argsort(kind, kind="stable")][n - shared : n - -(-percent * n // 100) + 1] & _CLEAR
                rows.append((n, int(rare[0].view(np.int64)), hashlib.md5((tokens & _CLEAR).tobytes()).digest(), rare.tobytes(), texts[i].as_py()))
            else:
                rows.append((n, None, None, None, None))
        columns = zip(*rows, strict=True) if rows else [[]] * 5
        return pa.table([ids, *(pa.array(x, t) for x, t in zip(columns, (pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.string()), strict=True))], names=["id", "n", "lead", "set", "rare", "text"])

    asked = dealt.groupBy("chunk").applyInArrow(ask, "chunk int, bucket int, blob binary")
    answers = asked.groupBy("bucket").applyInArrow(answer, "chunk int, bucket int, kinds binary")
    sets = dealt.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(measure, "id long, n long, lead long, set binary, rare binary, text string")
    sets = written(sets, "shingle-sets")
    nodes = sets.filter("set IS NOT NULL").groupBy("set").agg(F.min("id").alias("node"), F.count(F.lit(1)).alias("copies"), F.min_by(F.struct("n", "lead", "rare", "text"), "id").alias("own"))
    nodes = written(nodes.select("set", "node", "copies", "own.*"), "shingle-nodes")

    def meet(tokens: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct tokens and a node of each, and links between nodes that share one."""
        order = np.lexsort((own, tokens))
        tokens, own = tokens[order], own[order]
        first = firsts(tokens)
        a, b = united(own, np.repeat(own[first], np.diff(np.append(first, len(own)))))
        return tokens[first], own[first], a[a != b], b[a != b]

    def rare(batches):
        """Links within a flush go out at once; of each shingle one row travels on."""
        held, size_ = [], 0

        def send():
            tokens, own, a, b = meet(*(np.concatenate(x) for x in zip(*held, strict=True)))
            at = cuts(tokens, bits)
            found = np.flatnonzero(np.diff(at))
            blobs = [tokens[at[k] : at[k + 1]].tobytes() + own[at[k] : at[k + 1]].tobytes() for k in found]
            yield pa.RecordBatch.from_arrays([pa.nulls(len(a), pa.int32()), pa.array(a), pa.array(b), pa.nulls(len(a), pa.binary())], schema=edge_schema)
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), pa.nulls(len(found), pa.int64()), pa.nulls(len(found), pa.int64()), pa.array(blobs, pa.binary())], schema=edge_schema)

        for batch in batches:
            for node, blob in zip(batch.column(0).to_numpy(), batch.column(1), strict=True):
                tokens = np.frombuffer(blob.as_buffer(), np.uint64)
                held.append((tokens, np.full(len(tokens), node)))
                size_ += len(tokens)
                if size_ > 1_500_000:
                    yield from send()
                    held, size_ = [], 0
        if held:
            yield from send()

    edge_schema = pa.schema([("bucket", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("blob", pa.binary())])

    def gather(key, table):
        blobs = table.column("blob").to_pylist()
        tokens = np.concatenate([np.frombuffer(x, np.uint64, len(x) // 16) for x in blobs])
        own = np.concatenate([np.frombuffer(x, np.int64, len(x) // 16, len(x) // 2) for x in blobs])
        _, _, a, b = meet(tokens, own)
        return pa.table({"a": a, "b": b})

    sent = written(nodes.select("node", "rare").mapInArrow(rare, "bucket int, a long, b long, blob binary"), "rare-shingles")
    met = sent.filter("bucket IS NOT NULL").select("bucket", "blob").groupBy("bucket").applyInArrow(gather, "a long, b long")
    blocks = written(components(sent.filter("bucket IS NULL").select("a", "b").unionByName(met)), "shingle-blocks")

    members = blocks.join(nodes.select("node", "lead", "n"), "node")
    extent = members.groupBy("component").agg(F.count(F.lit(1)).alias("members"), F.sum("n").alias("shingles"), F.percentile_approx("lead", [k / PIECES for k in range(1, PIECES)], 1000).alias("edges"))
    # Pieces by content: between quantiles of the rarest shingle; where many share one, the pieces that it spans share them by
    # hash. Their number is a power of two, so that they are of one size.
    by_content = F.least(F.pow(F.lit(2.0), F.ceil(F.log2(F.greatest(F.col("members") / PIECE, F.lit(1.0))))), F.lit(PIECES)).cast("int")
    by_hash = F.greatest(F.ceil(F.col("shingles") / F.lit(PIECE_SHINGLES) / F.col("by_content")), F.lit(1)).cast("int")
    low, high = (F.size(F.filter("edges", lambda x: x < F.col("lead"))), F.size(F.filter("edges", lambda x: x <= F.col("lead"))))
    turn = low + F.pmod(F.xxhash64("node"), high - low + 1)
    placed = (
        members.join(extent, "component").withColumn("by_content", by_content).withColumn("by_hash", by_hash)
        .select("node", F.col("component").alias("block"), (F.col("by_content") * F.col("by_hash")).alias("pieces"), (F.floor(turn * F.col("by_content") / PIECES) * F.col("by_hash") + F.pmod(F.xxhash64("node", F.lit(1)), F.col("by_hash"))).cast("int").alias("piece"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)))
    )
    low, high = F.least("piece", "other"), F.greatest("piece", "other")
    # Small blocks are dealt out to as many groups as there are chunks of documents; a pair of pieces has a group of its own.
    task = F.when(F.col("pieces") == 1, F.pmod(F.xxhash64("block"), F.lit(deal.chunks + 255))).otherwise(F.xxhash64("block", low, high))
    tasks = placed.select("node", "block", "piece", low.alias("low"), high.alias("high"), task.alias("task"))

    def join(key, table):
        node, block, piece, low, high, copies = (table.column(c).to_numpy() for c in ("node", "block", "piece", "low", "high", "copies"))
        hashes, at = read(table)
        sets = [distinct(hashes[at[i] : at[i + 1]]) for i in range(len(node))]
        order = np.lexsort((high, low, block))
        a, b, partners = [], [], np.zeros(len(node), np.int64)
        for rows in np.split(order, firsts(block[order], low[order], high[order])[1:]):
            lo, hi = low[rows[0]], high[rows[0]]
            k = np.arange(len(rows))
            left, right = (k, k) if lo == hi else (k[piece[rows] == lo], k[piece[rows] == hi])
            links, linked, _ = tree_join([sets[i] for i in rows], left.tolist(), right.tolist(), percent, copies[rows])
            a += [node[rows[i]] for i, _ in links]
            b += [node[rows[j]] for _, j in links]
            partners[rows] += linked
        some = np.flatnonzero(partners)
        none = pa.nulls(len(some), pa.int64())
        counts = pa.table({"a": none, "b": none, "set": table.column("set").take(some), "partners": partners[some]})
        n = len(a)
        return pa.concat_tables([pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "set": pa.nulls(n, pa.binary()), "partners": pa.nulls(n, pa.int64())}), counts.cast(pa.schema([("a", pa.int64()), ("b", pa.int64()), ("set", pa.binary()), ("partners", pa.int64())]))])

    found = tasks.join(nodes.select("node", "set", "copies", "text"), "node").groupBy("task").applyInArrow(join, "a long, b long, set binary, partners long")
    found = written(found, "shingle-links")
    least = components(found.filter("set IS NULL").select("a", "b")).withColumnRenamed("component", "least")
    partners = found.filter("set IS NOT NULL").groupBy("set").agg(F.sum("partners").alias("partners"))
    known = nodes.select("set", "node", "copies").join(least, "node", "left").join(partners, "set", "left")
    # Written, so that the join with the documents stands on plain exchanges: Spark deals out a set that very many documents have.
    known = written(known.select("set", F.coalesce("least", "node").alias("least"), (F.col("copies") - 1 + F.coalesce("partners", F.lit(0))).alias("links")), "shingle-groups")
    done = sets.filter("set IS NOT NULL").select("id", "n", "set").join(known, "set").select("id", "n", "least", "links")
    done = done.unionByName(sets.filter("set IS NULL").select("id", "n", F.col("id").alias("least"), F.lit(0).cast("long").alias("links")))
    return done.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("least").alias("component_id"), F.col("links").alias("n_links"))


def keep_one(docs: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """Of each group of near copies the row with the least doc_id (all rows, if several have it), with the columns of `docs`.
    Rows with a null doc_id stay."""
    (gone,) = fresh(docs.columns, "later_copy")
    later = near_groups(docs, size, percent).filter("component_id != doc_id").select(F.col("doc_id").alias(gone)).distinct()
    return docs.join(later, named("doc_id").cast("long") == F.col(gone), "left_anti")


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_groups(docs)


SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(2, len(w) - 3))) AS i FROM d WHERE len(w) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id
), o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL
), l AS (SELECT a, b FROM o JOIN n x ON o.a = x.doc_id JOIN n y ON o.b = y.doc_id WHERE 100 * c >= 75 * (x.n + y.n - c)
), r AS (SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a
)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.b AS component_id, coalesce(k.links, 0)::BIGINT AS n_links
FROM d LEFT JOIN n USING (doc_id) JOIN (SELECT a, min(b) AS b FROM r GROUP BY a) m ON m.a = d.doc_id
LEFT JOIN (SELECT a, count(*) AS links FROM l GROUP BY a) k ON k.a = d.doc_id
"""
