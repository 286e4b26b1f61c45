"""Secret scans: fixed patterns, and sliding-window Shannon entropy per character class over candidate strings."""

from __future__ import annotations

import hashlib
import math
import re

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.llm.arrow import add_columns
from navgraph.llm.textscan import buffers

KINDS = ("assign", "access", "hex", "entropy")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{20,}")

#: Characters of a window, and the least entropy (bits a character) by class of the candidate.
WIDTH = 20
LEAST = {"hex": 2.8, "alnum": 3.4, "base64": 3.6}
#: Parts of candidates that are let pass: identifiers, paths and addresses, numbered names.
ALLOWED = (
    r"[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}",
    r"[A-Za-z]*[0-9]*",
    r"[0-9]+[A-Za-z]*",
    r"([A-Za-z]+|[0-9]+)([-_/=+]+([A-Za-z]+|[0-9]+))*[-_/=+]*",
)
#: Documented examples and runs of counting characters: no secret has them, and candidates are parted there.
DOCUMENTED = re.compile(r"EXAMPLE|example|0123456789|123456789|abcdefghij|ABCDEFGHIJ")

_table = lambda chars: bytes(0x78 if chr(i) in chars else 0x20 for i in range(256))
_HEX_RUN, _CANDIDATE_RUN = _table("0123456789abcdef"), _table("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-")
_KEYS = (b"passw", b"secret", b"token", b"apikey", b"api_key")
_LOG = [0.0, *(c * math.log2(c) for c in range(1, WIDTH + 1))]


def character_class(s: str) -> str:
    return "hex" if re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", s) else "alnum" if s.isalnum() else "base64"


def dense(s: str, least: float, width: int = WIDTH) -> tuple[int, int] | None:
    """From the first to the last window of `width` characters with at least `least` bits a character.

    Counts are kept as the window moves: one character leaves, one comes, and only their terms of the entropy change.
    """
    counts: dict[str, int] = {}
    total, first, last = 0.0, -1, -1
    for i, c in enumerate(s):
        if i >= width:
            gone = s[i - width]
            n = counts[gone]
            total += _LOG[n - 1] - _LOG[n]
            counts[gone] = n - 1
        n = counts.get(c, 0)
        total += _LOG[n + 1] - _LOG[n]
        counts[c] = n + 1
        if i >= width - 1 and math.log2(width) - total / width >= least:
            first, last = (i - width + 1 if first < 0 else first), i + 1
    return (first, last) if first >= 0 else None


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the fixed patterns, leftmost and non-overlapping within a kind."""
    found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    return sorted(found + [(m.start(), 2, m.end()) for m in HEX.finditer(text)])


def outside(start: int, end: int, taken: list[tuple[int, int]]):
    """The parts of start:end that none of the ascending spans covers."""
    for a, b in taken:
        if b > start and a < end:
            if a > start:
                yield start, a
            start = max(start, b)
    if start < end:
        yield start, end


def entropy_spans(text: str, base: list[tuple[int, int, int]], allowed: re.Pattern) -> list[tuple[int, int, int]]:
    """Dense runs of candidates that hold a letter and a digit. What a fixed pattern's span covers, or a documented example is,
    parts a candidate; each part is allowed or not by itself."""
    found = []
    for m in CANDIDATE.finditer(text):
        if text[max(0, m.start() - 3) : m.start()].endswith(("://", "www", "@")):
            continue
        taken = sorted([(a, b) for a, _, b in base if a < m.end() and m.start() < b] + [(d.start(), d.end()) for d in DOCUMENTED.finditer(text, m.start(), m.end())])
        for a, b in outside(m.start(), m.end(), taken):
            s = text[a:b]
            if len(s) >= WIDTH and not allowed.fullmatch(s) and (part := dense(s, LEAST[character_class(s)])):
                found.append((a + part[0], 3, a + part[1]))
    return found


def spelled(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def find(text: bytes, allowed: re.Pattern) -> tuple[list, list]:
    """Base spans and all spans of a text in UTF-8. Plain byte searches rule out most texts first; they miss none."""
    low, run = text.lower(), b"x" * 20
    if not (any(k in low for k in _KEYS) or b"AKIA" in text or b"x" * 24 in text.translate(_HEX_RUN) or run in text.translate(_CANDIDATE_RUN)):
        return [], []
    s = text.decode("utf-8", "replace")
    base = base_spans(s)
    return base, sorted(base + entropy_spans(s, base, allowed))


def scan(docs: DataFrame, allow_list: tuple[str, ...] = ALLOWED) -> DataFrame:
    """Adds n_assign, n_access, n_hex, n_entropy, base_sha256, spans and redacted to `docs`, which needs text.

    Offsets count code points, end exclusive. redacted is the text with every span replaced by "[secret]" (null stays
    null). Null and empty texts have no spans; ties of start are ordered by kind as listed in KINDS.
    """

    def make():
        allowed = re.compile("|".join(f"(?:{x})" for x in allow_list))

        def work(batch):
            column = batch.column(batch.schema.get_field_index("text"))
            data, offsets = buffers(column)
            counts, sha, all_spans, redacted = np.zeros((len(offsets) - 1, 4), np.int64), [], [], {}
            for i in range(len(offsets) - 1):
                text = data[offsets[i] : offsets[i + 1]].tobytes()
                base, spans = find(text, allowed)
                sha.append(hashlib.sha256(spelled(base).encode()).hexdigest())
                all_spans.append(spelled(spans))
                if spans:
                    np.add.at(counts[i], [k for _, k, _ in spans], 1)
                    redacted[i] = without(text.decode("utf-8", "replace"), spans)
            out = {f"n_{k}": counts[:, j].tolist() for j, k in enumerate(KINDS)}
            return out | {"base_sha256": sha, "spans": all_spans, "redacted": [redacted.get(i) for i in range(len(offsets) - 1)]}

        return work

    found = add_columns(docs, "n_assign long, n_access long, n_hex long, n_entropy long, base_sha256 string, spans string, redacted string", make)
    return found.withColumn("redacted", F.coalesce("redacted", "text"))


def without(text: str, spans: list[tuple[int, int, int]]) -> str:
    out, at = [], 0
    for a, _, b in spans:
        if a >= at:
            out += [text[at:a], "[secret]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def redact(docs: DataFrame) -> DataFrame:
    """`docs` with secrets replaced in text, and n_chars (if there) counted anew where text changed."""
    found = scan(docs)
    new = {"text": F.col("redacted")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("spans") != "", F.length("redacted").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    return found.select(*(new.get(c, F.col(c)).alias(c) for c in docs.columns))


def op7_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return scan(docs).select("doc_id", "n_assign", "n_access", "n_hex", "n_entropy", "base_sha256", "spans")
