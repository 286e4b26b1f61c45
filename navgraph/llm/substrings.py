"""Removing repeated passages, with automata of recurring phrases.

Two equal windows of WINDOW words choose the same anchor, the least hash among their phrases of GRAM words.

1. Chunks of documents ask buckets of anchors which of theirs recur.
2. A chunk sends each of its windows with a recurring anchor once, with its first place, to the bucket of the anchor (of the
   window itself, where very many windows share an anchor). The bucket confirms those that recur and says whether a window's
   first place of all is in this chunk.
3. The chunk compiles an Aho-Corasick automaton of the anchor phrases of its confirmed windows, streams all its documents
   through it, and looks at every window around every phrase that is found: a confirmed one is for removal unless it stands
   at its first place.

Windows are told apart by 64 bits of hash within one anchor of 45 to 58 bits. Nothing is broadcast; a passage that a third of
all documents share is sent once by each chunk.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, IntegerType, LongType, StringType, StructField, StructType

from navgraph.llm.arrow import named
from navgraph.llm.deal import bucket_of, counted, deal_of, firsts, mask, packed, totals, unpack
from navgraph.llm.textscan import GRAPHIC, Words, mix, words
from navgraph.session import ship

WINDOW, GRAM = 20, 8
#: Bytes of an anchor below its bucket's bits; places of an anchor from which on its windows are dealt by their own hashes.
WIDTH, HOT = 5, 1000
#: Characters of a digit of a word's number in an automaton.
BASE = 64
_PLACE = 20


def anchors(w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Places of all windows, the anchor of each, the anchor's place, and whether it is another than the window's before."""
    at, _ = w.grams(WINDOW)
    if not len(at):
        return at, np.zeros(0, np.uint64), at, np.zeros(0, bool)
    place, hashes = w.grams(GRAM)
    low = np.full(len(w.hashes), np.iinfo(np.uint64).max, np.uint64)
    low[place] = (hashes >> np.uint64(_PLACE) << np.uint64(_PLACE)) | (place.astype(np.uint64) & np.uint64((1 << _PLACE) - 1))
    wide, have = WINDOW - GRAM + 1, 1
    while 2 * have <= wide:
        low = np.minimum(low[:-have], low[have:])
        have *= 2
    if wide > have:
        low = np.minimum(low[: len(low) - (wide - have)], low[wide - have :])
    key = low[at]
    new = np.concatenate(([True], (key[1:] != key[:-1]) | (at[1:] != at[:-1] + 1)))
    inner = ((key & np.uint64((1 << _PLACE) - 1)).astype(np.int64) - at) & ((1 << _PLACE) - 1)
    return at, mix(key >> np.uint64(_PLACE)), at + inner, new


class Phrases:
    """An Aho-Corasick automaton over words, for distinct phrases given as rows of word hashes. A word that some phrase has is a number of
    as many digits as are needed, each place with characters of its own, so that no node has many edges (they are searched one by one)
    and nothing is found across words. Of a text, runs of such words that are long enough for a phrase go through it."""

    def __init__(self, phrases: np.ndarray):
        import ahocorasick

        self.known, number = np.unique(phrases, return_inverse=True)
        self.size, self.digits = phrases.shape[1], 1
        while BASE**self.digits < len(self.known):
            self.digits += 1
        self.may = np.zeros(1 << 20, bool)
        self.may[(self.known & np.uint64((1 << 20) - 1)).astype(np.int64)] = True
        self.made = ahocorasick.Automaton()
        lines, step = self._text(number.ravel()), self.size * self.digits
        for i in range(len(phrases)):
            self.made.add_word(lines[i * step : (i + 1) * step], i)
        self.made.make_automaton()

    def _text(self, numbers: np.ndarray) -> str:
        """-1 stands between runs."""
        place = np.arange(self.digits)
        digits = numbers[:, None] // BASE ** (self.digits - 1 - place) % BASE + BASE * place + 1
        return np.where(numbers[:, None] < 0, 0xE000, digits).astype(np.uint32).tobytes().decode("utf-32-le")

    def find(self, w: Words) -> np.ndarray:
        """First words of all phrases in the documents of w; none reaches over a document's end."""
        number = np.full(len(w.hashes), -1)
        may = np.flatnonzero(self.may[(w.hashes & np.uint64((1 << 20) - 1)).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.known, w.hashes[may]), len(self.known) - 1)
        same = self.known[at] == w.hashes[may]
        number[may[same]] = at[same]
        there = np.zeros(len(number) + 2, bool)
        there[1:-1] = number >= 0
        edge = np.zeros(len(number) + 1, bool)
        edge[w.offsets] = True
        begin, end = np.flatnonzero(there[1:] & (~there[:-1] | edge)), np.flatnonzero(there[:-1] & (~there[1:] | edge))
        long_ = end - begin >= self.size
        begin, n = begin[long_], (end - begin)[long_] + 1  # and the place after each run
        if not len(begin):
            return begin
        back = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n - begin, n)
        own = number[np.minimum(back, len(number) - 1)]
        own[np.cumsum(n) - 1] = -1
        ends = np.fromiter((e for e, _ in self.made.iter(self._text(own))), np.int64) // self.digits
        return back[ends] - self.size + 1


class Passages:
    """Windows of a chunk whose anchors recur, each once, at its first place in the chunk. Documents stand in the order of id and text, so
    that every reading gives the same."""

    def __init__(self, ids: np.ndarray, texts: pa.Array, kinds, cut: np.uint64):
        """kinds: of masked anchors (an array), 0 where one doesn't recur, 2 where it is hot."""
        self.ids, self.steps, parts = ids, [], []
        for w in words(texts, GRAPHIC):
            at, values, place, new = anchors(w)
            self.steps.append(w)
            values = values & cut
            kind = kinds(values[new])[np.cumsum(new) - 1] if len(at) else np.zeros(0, np.uint8)
            may = kind > 0
            at, own = at[may], np.repeat(np.arange(len(w.offsets) - 1), w.counts)[at[may]]
            step = np.full(len(at), len(self.steps) - 1)
            parts.append((w.spans(at, at + WINDOW), values[may], kind[may], ids[w.first + own], at - w.offsets[own], w.first + own, place[may], step))
        joined = [np.concatenate(x) for x in zip(*parts, strict=True)] if parts else [np.zeros(0, np.int64)] * 8
        order = np.argsort(joined[0], kind="stable")
        first = firsts(joined[0][order])
        several = np.diff(np.append(first, len(order))) > 1
        keep = order[first]
        back = np.argsort(keep)
        self.hash, self.anchor, self.kind, self.id, self.start, self.row, self.place, self.step = (x[keep[back]] for x in joined)
        self.several = several[back]

    def route(self, bits: int) -> tuple[np.ndarray, np.ndarray]:
        """Windows by bucket, and the bucket of each."""
        bucket = np.where(self.kind == 2, bucket_of(mix(self.hash), bits), bucket_of(self.anchor, bits))
        order = np.argsort(bucket, kind="stable")
        return order, bucket[order]

    def sent(self, bits: int) -> tuple[list[int], list[bytes]]:
        """One value per bucket: runs of windows that follow each other, with anchor, document, start and length; and the windows."""
        order, bucket = self.route(bits)
        anchor, row, start = self.anchor[order], self.row[order], self.start[order]
        new = np.ones(len(order), bool)
        new[1:] = (bucket[1:] != bucket[:-1]) | (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1]) | (start[1:] != start[:-1] + 1)
        begin = np.flatnonzero(new)
        size, owner = np.diff(np.append(begin, len(order))), bucket[begin]
        edge = np.append(firsts(owner), len(begin))
        out: tuple[list[int], list[bytes]] = ([], [])
        for a, b in zip(edge[:-1], edge[1:], strict=True):
            i = order[begin[a] : begin[b] if b < len(begin) else len(order)]
            s = order[begin[a:b]]
            out[0].append(int(owner[a]))
            out[1].append(b"".join((np.array([b - a, len(i)], np.int64).tobytes(), self.anchor[s].tobytes(), self.id[s].astype(np.int64).tobytes(), self.start[s].astype(np.int32).tobytes(), size[a:b].astype(np.int32).tobytes(), self.several[i].tobytes(), self.hash[i].tobytes())))
        return out

    def removed(self, codes: np.ndarray, bits: int):
        """For every step: its words, and which of them go. codes: the buckets' answers, in the order of sending."""
        code = np.zeros(len(self.hash), np.uint8)
        code[self.route(bits)[0]] = codes
        sure = np.flatnonzero(code)
        if not len(sure):
            yield from ((w, np.zeros(len(w.hashes), bool)) for w in self.steps)
            return
        some = sure[firsts(*(x[sure] for x in (self.step, self.place)))]
        places = [self.place[some[self.step[some] == k]] for k in range(len(self.steps))]
        phrases = np.concatenate([w.hashes[at[:, None] + np.arange(GRAM)] for w, at in zip(self.steps, places, strict=True)])
        _, one = np.unique(np.concatenate([w.spans(at, at + GRAM) for w, at in zip(self.steps, places, strict=True)]), return_index=True)
        found = Phrases(phrases[one])
        sure = sure[np.argsort(self.hash[sure])]
        hashes = self.hash[sure]
        for w in self.steps:
            near, n = np.zeros(len(w.hashes) + 1, np.int64), len(w.hashes)
            at = found.find(w)
            np.add.at(near, np.maximum(at - (WINDOW - GRAM), 0), 1)
            np.add.at(near, at + 1, -1)
            start = np.flatnonzero(np.cumsum(near[:-1]) > 0)
            own = np.repeat(np.arange(len(w.offsets) - 1), w.counts)[start]
            inside = start + WINDOW <= w.offsets[own + 1]
            start, own = start[inside], own[inside]
            h = w.spans(start, start + WINDOW)
            place = np.minimum(np.searchsorted(hashes, h), len(hashes) - 1)
            which = sure[place]
            gone = (hashes[place] == h) & ((code[which] == 2) | (self.id[which] != self.ids[w.first + own]) | (self.start[which] != start - w.offsets[own]))
            cover = np.zeros(n + 1, np.int64)
            np.add.at(cover, start[gone], 1)
            np.add.at(cover, start[gone] + WINDOW, -1)
            yield w, np.cumsum(cover[:-1]) > 0


def judged(blobs: list[bytes]) -> list[bytes]:
    """For every window of every blob: 0 if it is the only one of its words, 1 if this is its first place, else 2."""
    parts = []
    for k, blob in enumerate(blobs):
        runs, n = (int(x) for x in np.frombuffer(blob, np.int64, 2))
        at = 16 + 24 * runs
        size = np.frombuffer(blob, np.int32, runs, 16 + 20 * runs)
        inner = np.arange(n) - np.repeat(np.cumsum(size) - size, size)
        parts.append((np.frombuffer(blob, np.uint64, n, at + n), np.repeat(np.frombuffer(blob, np.uint64, runs, 16), size), np.repeat(np.frombuffer(blob, np.int64, runs, 16 + 8 * runs), size), np.repeat(np.frombuffer(blob, np.int32, runs, 16 + 16 * runs), size) + inner, np.frombuffer(blob, bool, n, at)))
    hashes, anchor, ids, start, several = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.lexsort((start, ids, anchor, hashes))
    first = firsts(hashes[order], anchor[order])
    size = np.diff(np.append(first, len(order)))
    recurs = np.repeat((size > 1) | np.logical_or.reduceat(several[order], first), size)
    head = np.repeat(order[first], size)
    code = np.empty(len(order), np.uint8)
    code[order] = np.where(recurs, np.where((ids[order] == ids[head]) & (start[order] == start[head]), 1, 2), 0)
    return [x.tobytes() for x in np.split(code, np.cumsum([len(p[0]) for p in parts])[:-1])]


def dedup(docs: DataFrame, with_text: bool = True) -> DataFrame:
    """Adds n_words, n_removed, kept_sha256 and, with_text, kept (the words that stay, joined by blanks) to `docs`.

    A word goes if it lies in a window of WINDOW words of its document whose words also start earlier: in a smaller doc_id, or
    before it in the same one. Windows are judged on the input. Needs doc_id (whole numbers; null comes before all) and
    text (null has no words). Rows that share a doc_id are one document to each other: neither makes the other's windows at
    the same start go. Texts of fewer than WINDOW words stay whole. Other columns stay, those of the four names are replaced.
    An empty table gives an empty result.
    """
    spark = docs.sparkSession
    ship(spark)
    new = [StructField("n_words", LongType()), StructField("n_removed", LongType()), StructField("kept_sha256", StringType()), StructField("kept", StringType())][: 4 if with_text else 3]
    keep = [f for f in docs.schema.fields if f.name.lower() not in {"n_words", "n_removed", "kept_sha256", "kept"}]
    # Names of the table don't take part in what follows: they may clash, and grouped functions take none with dots.
    at_id, at_chunk, at_text, inner = "id", "chunk", "body", [StructField(f"own{k}", f.dataType) for k, f in enumerate(keep)]
    deal = deal_of(docs)
    bits, cut = deal.bits, mask(deal.bits, WIDTH)
    dealt = docs.select(*(named(f.name).alias(i.name) for f, i in zip(keep, inner, strict=True)), F.coalesce(named("doc_id").cast("long"), F.lit(-(1 << 63))).alias(at_id), named("text").alias(at_text)).withColumn(at_chunk, deal.chunk(at_id, at_text))

    def ordered(table):
        return table.take(pc.sort_indices(table, [(at_id, "ascending"), (at_text, "ascending")]))

    def ask(key, table):
        found = []
        for w in words(table.column(at_text), GRAPHIC):
            _, values, _, new_ = anchors(w)
            found.append(values[new_] & cut)
        buckets, blobs = packed(*counted(np.concatenate(found) if found else np.zeros(0, np.uint64)), bits, WIDTH)
        return pa.table({"chunk": pa.array([key[0].as_py()] * len(blobs), pa.int32()), "bucket": pa.array(buckets, pa.int32()), "blob": pa.array(blobs, pa.binary())})

    def answer(key, table):
        parts = [unpack(x, key[0].as_py(), bits, WIDTH) for x in table.column("blob").to_pylist()]
        _, n, place = totals(parts)
        kinds = ((n > 1).astype(np.uint8) + (n >= HOT))[place]
        return pa.table({"chunk": table.column("chunk"), "bucket": table.column("bucket"), "blob": pa.array([x.tobytes() for x in np.split(kinds, np.cumsum([len(h) for h, _ in parts])[:-1])], pa.binary())})

    def passages(table, answers) -> Passages:
        """Of an ordered table; answers: rows of kind 0 hold the kinds of anchors by bucket."""
        texts = table.column(at_text).combine_chunks()
        asked = [anchors(w) for w in words(texts, GRAPHIC)]
        known, _ = counted(np.concatenate([values[new_] & cut for _, values, _, new_ in asked]) if asked else np.zeros(0, np.uint64))
        own = np.frombuffer(b"".join(answers.sort_by("bucket").column("blob").to_pylist()), np.uint8)
        return Passages(table.column(at_id).to_numpy(), texts, lambda values: own[np.searchsorted(known, values)], cut)

    def send(key, table, answers):
        buckets, blobs = passages(ordered(table), answers).sent(bits)
        return pa.table({"chunk": pa.array([key[0].as_py()] * len(blobs), pa.int32()), "bucket": pa.array(buckets, pa.int32()), "blob": pa.array(blobs, pa.binary())})

    def judge(key, table):
        return pa.table({"chunk": table.column("chunk"), "bucket": table.column("bucket"), "blob": pa.array(judged(table.column("blob").to_pylist()), pa.binary())})

    schema = StructType([*inner, *new])

    def remove(key, table, answers):
        from pyspark.sql.pandas.types import to_arrow_schema

        table = ordered(table)
        first, second = (answers.filter(pc.equal(answers.column("turn"), k)).select(["bucket", "blob"]) for k in (0, 1))
        codes = np.frombuffer(b"".join(second.sort_by("bucket").column("blob").to_pylist()), np.uint8)
        n_words, n_removed, sha, kept = [], [], [], []
        texts = table.column(at_text).combine_chunks()
        for w, gone in passages(table, first).removed(codes, bits):
            for i in range(len(w.offsets) - 1):
                text, own = texts[w.first + i], gone[w.offsets[i] : w.offsets[i + 1]]
                parts = text.as_buffer().to_pybytes().split() if text.is_valid else []
                n_words.append(len(parts))
                if own.any():
                    parts = [parts[k] for k in np.flatnonzero(~own)]
                n_removed.append(n_words[-1] - len(parts))
                whole = b" ".join(parts)
                sha.append(hashlib.sha256(whole).hexdigest())
                kept.append(whole.decode("utf-8", "replace") if with_text else None)
        made = [pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(sha, pa.string()), pa.array(kept, pa.string())][: len(new)]
        types = to_arrow_schema(StructType(new))
        return pa.table([*(table.column(f.name) for f in inner), *(m.cast(t.type) for m, t in zip(made, types, strict=True))], names=[f.name for f in schema])

    row = StructType([StructField("chunk", IntegerType()), StructField("bucket", IntegerType()), StructField("blob", BinaryType())])
    kinds = dealt.groupBy(at_chunk).applyInArrow(ask, row).groupBy("bucket").applyInArrow(answer, row)
    codes = dealt.groupBy(at_chunk).cogroup(kinds.groupBy("chunk")).applyInArrow(send, row).groupBy("bucket").applyInArrow(judge, row)
    both = kinds.withColumn("turn", F.lit(0)).unionByName(codes.withColumn("turn", F.lit(1)))
    found = dealt.groupBy(at_chunk).cogroup(both.groupBy("chunk")).applyInArrow(remove, schema)
    return found.select(*(F.col(i.name).alias(f.name) for f, i in zip(keep, inner, strict=True)), *(f.name for f in new))


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup(docs, with_text=False).select("doc_id", "n_words", "n_removed", "kept_sha256")


SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), o AS (
  SELECT doc_id, i, md5(array_to_string(w[i : i + 19], ' ')) AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS i FROM d WHERE len(w) >= 20)
), r AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS k FROM o) WHERE k > 1
), h AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + 20)) AS k FROM r
), g AS (SELECT doc_id, list(k) AS ks, count(*) AS n FROM h GROUP BY doc_id
), words AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS k FROM d
), kept AS (
  SELECT words.doc_id, string_agg(word, ' ' ORDER BY words.k) AS t FROM words LEFT JOIN h ON words.doc_id = h.doc_id AND words.k = h.k WHERE h.k IS NULL GROUP BY words.doc_id
)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(g.n, 0)::BIGINT AS n_removed, sha256(coalesce(kept.t, '')) AS kept_sha256
FROM d LEFT JOIN g USING (doc_id) LEFT JOIN kept USING (doc_id)
"""
