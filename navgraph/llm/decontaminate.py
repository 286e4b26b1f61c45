"""Benchmark decontamination by one Aho-Corasick automaton over normalised test items.

Every item gives its windows of ten consecutive words as patterns of one automaton. A document is normalised the same way
and read once; a match's end gives word numbers, and those give places in the original text.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.llm.arrow import add_columns, fresh, named
from navgraph.llm.textscan import ALNUM, LOWER, buffers
from navgraph.session import written

WINDOW = 10
#: Most bytes of benchmark text that are sent to the workers at once; the automaton takes a fixed multiple of it.
MAX_BYTES = 64 << 20

#: Lower-cases A-Z and makes a blank of what separates words, byte by byte, so that places stay.
NORMAL = bytes(np.where(ALNUM[LOWER], LOWER, 0x20).astype(np.uint8))


def normalised(text: bytes) -> tuple[str, int]:
    """The words with single blanks around them, one character a byte, and their number."""
    found = text.translate(NORMAL).split()
    return f" {b' '.join(found).decode('latin-1')} ", len(found)


def windows(items: list[tuple[str, str]], window: int) -> dict[str, tuple[int, list[int]]]:
    """Each window's words, length and items (places in `items`). A shorter item is one window; one without words has none."""
    found: dict[str, tuple[int, list[int]]] = {}
    for k, (_, text) in enumerate(items):
        parts = (text or "").encode().translate(NORMAL).split()
        for i in range(max(1, len(parts) - window + 1) if parts else 0):
            part = parts[i : i + window]
            own = found.setdefault(f" {b' '.join(part).decode('latin-1')} ", (len(part), []))[1]
            if not own or own[-1] != k:
                own.append(k)
    return found


def automaton(items: list[tuple[str, str]], window: int):
    import ahocorasick

    made = ahocorasick.Automaton()
    for pattern, value in windows(items, window).items():
        made.add_word(pattern, value)
    if len(made):
        made.make_automaton()
    return made


def characters(text: bytes, places: np.ndarray) -> np.ndarray:
    """Code points before each byte place."""
    lead = np.zeros(len(text) + 1, np.int64)
    np.cumsum((np.frombuffer(text, np.uint8) & 0xC0) != 0x80, out=lead[1:])
    return lead[places]


def scan(docs: DataFrame, items: DataFrame, window: int = WINDOW, max_bytes: int = MAX_BYTES) -> DataFrame:
    """Adds n_words, n_hit, items (sorted as strings), contaminated and spans (of the original text) to `docs`.

    docs needs text; items needs item_id and text. A word is hit if it lies in an occurrence of any window. spans are runs of
    hit words as code point offsets, end exclusive. Null or wordless texts have no words and no hits; repeated items count
    once; a null item_id reads "null"; no items hit nothing. Other columns stay, those of the five names are replaced.

    At most about `max_bytes` bytes of benchmark are sent to the workers at once. A larger one is dealt by hash into parts, and the
    documents are read once for each: what a part hits goes along to the next.
    """
    spark = docs.sparkSession
    items = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item_id"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(1, -(-size // max_bytes))
    own = [c for c in docs.columns if c.lower() not in ("n_words", "n_hit", "items", "contaminated", "spans")]
    (marks,) = fresh([*docs.columns, "n_words", "n_hit", "items", "contaminated", "spans"], "hit_words")
    found = docs.select(*map(named, own))
    if parts > 1:
        found = found.withColumns({marks: F.lit(None).cast("binary"), "items": F.array().cast("array<string>")})
    for part in range(parts):
        rows = [tuple(r) for r in items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == part).collect()]
        sent = spark.sparkContext.broadcast(rows)
        last = part == parts - 1

        def make(sent=sent, last=last):
            items, made = sent.value, automaton(sent.value, window)

            def work(batch):
                data, offsets = buffers(batch.column(batch.schema.get_field_index("text")))
                before = batch.schema.get_field_index(marks)
                n_words, n_hit, ids, spans, masks = [], [], [], [], []
                for i in range(len(offsets) - 1):
                    text = data[offsets[i] : offsets[i + 1]].tobytes()
                    plain, n = normalised(text)
                    mask = batch.column(before)[i].as_py() if before >= 0 else None
                    known = batch.column(batch.schema.get_field_index("items"))[i].as_py() if before >= 0 else []
                    hits = list(made.iter(plain)) if n and len(made) else []
                    n_words.append(n)
                    if not hits and mask is None:
                        n_hit.append(0)
                        ids.append([])
                        spans.append([])
                        masks.append(None)
                        continue
                    hit = np.unpackbits(np.frombuffer(mask, np.uint8), count=n).astype(bool) if mask is not None else np.zeros(n, bool)
                    if hits:
                        blanks = np.flatnonzero(np.frombuffer(plain.encode("latin-1"), np.uint8) == 0x20)
                        ends = np.searchsorted(blanks, [end for end, _ in hits])
                        edge = np.zeros(n + 1, np.int64)
                        np.add.at(edge, ends - [k for _, (k, _) in hits], 1)
                        np.add.at(edge, ends, -1)
                        hit |= np.cumsum(edge[:-1]) > 0
                    ids.append(sorted({*known, *(items[x][0] for _, (_, own) in hits for x in own)}))
                    masks.append(np.packbits(hit).tobytes())
                    n_hit.append(int(hit.sum()))
                    spans.append(_spans(text, hit) if last else [])
                out = {"n_words": n_words, "n_hit": n_hit, "items": ids, "contaminated": [x > 0 for x in n_hit], "spans": spans}
                return out if last else {marks: masks, "items": ids}

            return work

        if last:
            found = add_columns(found, "n_words long, n_hit long, items array<string>, contaminated boolean, spans array<struct<start:long,end:long>>", make)
        else:
            found = written(add_columns(found, f"{marks} binary, items array<string>", make), "benchmark-hits")
            sent.destroy()
    return found.select(*map(named, own), "n_words", "n_hit", "items", "contaminated", "spans")


def _spans(text: bytes, hit: np.ndarray) -> list[dict]:
    """Runs of hit words, as code point offsets of the text."""
    step = np.diff(np.concatenate(([0], hit.astype(np.int8), [0])))
    inside = np.frombuffer(text.translate(NORMAL), np.uint8) != 0x20
    turn = np.diff(np.concatenate(([0], inside.astype(np.int8), [0])))
    first, last = np.flatnonzero(turn == 1)[np.flatnonzero(step == 1)], np.flatnonzero(turn == -1)[np.flatnonzero(step == -1) - 1]
    return [{"start": int(a), "end": int(b)} for a, b in zip(characters(text, first), characters(text, last), strict=True)]


def clean(docs: DataFrame, items: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents without any hit, with the columns they came with."""
    return scan(docs, items, window).filter(~F.col("contaminated")).select(*map(named, docs.columns))


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = scan(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), p AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS s
  FROM (SELECT *, unnest(range(1, greatest(1, len(w) - 9) + 1)) AS i FROM b WHERE len(w) > 0)
), lengths AS (SELECT DISTINCT n FROM p
), o AS (
  SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS s
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, lengths WHERE len(w) >= n)
), m AS (SELECT DISTINCT o.doc_id, o.n, o.i, p.item_id FROM o JOIN p ON o.n = p.n AND o.s = p.s
), h AS (SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS k FROM m) GROUP BY doc_id
), t AS (SELECT doc_id, count(*) AS n_items, sha256(string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR)) AS s FROM (SELECT DISTINCT doc_id, item_id FROM m) GROUP BY doc_id
)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       coalesce(t.s, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)
"""
