"""Language identification by a bidirectional gated recurrent network over bytes.

A text is cut into runs of RUN bytes, whatever words or lines they hold. The network reads each run from both ends and labels
every byte, so that a label rests on the bytes of the run before and after it, in other words as well. A document's
probabilities are the softmax of the mean of its bytes' log-probabilities. Runs begin at a document's start, so a label doesn't
depend on where a batch begins.

Arrays have time first, then direction, then feature, and runs last: each step is a few operations over contiguous rows.
"""

from __future__ import annotations

import io
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.llm.arrow import add_columns
from navgraph.llm.textscan import buffers
from navgraph.session import ship

RUN, HIDDEN, EMBED = 192, 24, 12
#: Expected labelled documents per language, and runs of so many bytes per language, that the network learns from.
TRAIN_DOCS, TRAIN_RUNS, TRAIN_BYTES = 300, 1500, 96
EPOCHS, BATCH, RATE = 3, 192, 0.01
#: Runs that are labelled together, and bytes of text that are cut into runs together.
TOGETHER, STEP = 512, 1 << 20
UNKNOWN = "und"
NONE = 256


class Network:
    """Bytes to a distribution over `labels` at every position.

    Gates are z, r = (1 + tanh(a)) / 2 with a from state, embedded byte and 1; the candidate is c = tanh(from byte and 1 +
    r * (from state)); the state goes to state + z * (c - state). The second direction reads time backwards.
    """

    PARTS = ("embed", "gates", "given", "state", "out", "bias")

    def __init__(self, labels: list[str], seed: int = 7, hidden: int = HIDDEN, embed: int = EMBED):
        rng, n = np.random.default_rng(seed), hidden
        drawn = lambda *shape: rng.standard_normal(shape).astype(np.float32)
        self.labels, self.n, self.e = labels, n, embed
        self.embed = drawn(257, embed) * np.float32(0.5)
        self.gates = drawn(2, 2 * n, n + embed + 1) * np.float32(0.5 / np.sqrt(n))
        self.given = drawn(2, n, embed + 1) / np.float32(np.sqrt(embed))
        self.state = drawn(2, n, n) / np.float32(np.sqrt(n))
        self.out = drawn(2, len(labels), n) / np.float32(np.sqrt(2 * n))
        self.bias = np.zeros((len(labels), 1), np.float32)

    def dumped(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, labels=np.array([x.encode() for x in self.labels]), size=np.array([self.n, self.e]), **{k: getattr(self, k) for k in self.PARTS})
        return out.getvalue()

    @classmethod
    def loaded(cls, data: bytes) -> Network:
        with np.load(io.BytesIO(data)) as parts:
            made = cls([x.decode() for x in parts["labels"].tolist()], 0, *parts["size"].tolist())
            for k in cls.PARTS:
                setattr(made, k, parts[k])
        return made

    def _states(self, x: np.ndarray, mask: np.ndarray | None, kept: list | None = None) -> np.ndarray:
        """x: time x runs, NONE where there is no byte (there mask is 0, and the state stays). Returns (time + 1) x 2 x
        (state, embedded byte, 1) x runs; states stand one place after the byte that was read last."""
        time, runs = x.shape
        n, e = self.n, self.e
        all_ = np.empty((time + 1, 2, n + e + 1, runs), np.float32)
        all_[0, :, :n], all_[:, :, n + e] = 0, 1
        own = self.embed[x].transpose(0, 2, 1)
        all_[:time, 0, n : n + e], all_[:time, 1, n : n + e] = own, own[::-1]
        given = np.matmul(self.given, all_[:time, :, n:])
        gates, from_state = np.empty((2, 2 * n, runs), np.float32), np.empty((2, n, runs), np.float32)
        half = np.float32(0.5)
        for t in range(time):
            if kept is not None:
                gates, from_state = np.empty_like(gates), np.empty_like(from_state)
            before, c = all_[t, :, :n], given[t]
            np.matmul(self.gates, all_[t], out=gates)
            np.tanh(gates, out=gates)
            gates += 1
            gates *= half
            np.matmul(self.state, before, out=from_state)
            z, r = gates[:, :n], gates[:, n:]
            step = r * from_state
            c += step
            np.tanh(c, out=c)
            np.subtract(c, before, out=step)
            step *= z
            if mask is not None and not (mask[t].all() and mask[time - 1 - t].all()):
                step *= np.stack((mask[t], mask[time - 1 - t]))[:, None]
            np.add(before, step, out=all_[t + 1, :, :n])
            if kept is not None:
                kept.append((gates, from_state, c))
        return all_

    def _logits(self, states: np.ndarray) -> np.ndarray:
        """time x labels x runs."""
        n = self.n
        return np.matmul(self.out[0], states[1:, 0, :n]) + np.matmul(self.out[1], states[:0:-1, 1, :n]) + self.bias

    def _joined(self) -> np.ndarray:
        """2 x (gates, candidate from state, candidate from byte and 1, labels) x (state, embedded byte, 1): all that a step multiplies
        its state and byte by. Gates and candidate come times -2, as the exponents that tanh and the gates are taken by."""
        none = lambda m, columns: np.zeros((2, m.shape[1], columns), m.dtype)
        from_state, given = np.concatenate((self.state, none(self.state, self.e + 1)), 2), np.concatenate((none(self.given, self.n), self.given), 2)
        to_labels = np.concatenate((self.out, none(self.out, self.e + 1)), 2)
        return np.concatenate((*(np.float32(-2) * m for m in (self.gates, from_state, given)), to_labels), 1)

    def log_probabilities(self, x: np.ndarray) -> np.ndarray:
        """time x labels x runs, for x of time x runs. The same steps as _states(), in place: no state outlives the next one but in
        its share of the logits, so that all a step touches stays in the processor's cache. A step is one product; numpy's tanh looks
        up tables, slowly on some processors, so (1 + tanh(a)) / 2 is 1 / (1 + exp(-2 a)), where an exponential too large gives 0."""
        (time, runs), n, e = x.shape, self.n, self.e
        mask = x < NONE
        full = mask.all(1)
        full &= full[::-1]
        now = np.zeros((2, n + e + 1, runs), np.float32)
        now[:, n + e] = 1
        state = now[:, :n]
        embed, x = np.ascontiguousarray(self.embed.T, np.float32), x.astype(np.intp)
        one, two = np.float32(1), np.float32(2)
        joined, made = self._joined(), np.empty((2, 4 * n + len(self.labels), runs), np.float32)
        gates, z, r, inner, c, share = made[:, : 2 * n], made[:, :n], made[:, n : 2 * n], made[:, 2 * n : 3 * n], made[:, 3 * n : 4 * n], made[:, 4 * n :]
        ahead = np.empty((time, 2, len(self.labels), runs), np.float32)
        with np.errstate(over="ignore"):
            for t in range(time):
                for way, at in enumerate((t, time - 1 - t)):
                    np.take(embed, x[at], 1, out=now[way, n : n + e], mode="clip")
                np.matmul(joined, now, out=made)
                if t:
                    ahead[t - 1] = share  # of the state before this step
                np.exp(gates, out=gates)
                gates += one
                np.divide(one, gates, out=gates)
                inner *= r
                c += inner
                np.exp(c, out=c)
                c += one
                np.divide(two, c, out=c)
                c -= one
                c -= state
                c *= z
                if not full[t]:
                    c *= np.stack((mask[t], mask[time - 1 - t]))[:, None]
                state += c
        if time:
            np.matmul(self.out, state, out=ahead[time - 1])
        logits = ahead[:, 0] + ahead[::-1, 1]
        logits += self.bias
        logits -= logits.max(1, keepdims=True)
        logits -= np.log(np.exp(logits).sum(1, keepdims=True))
        return logits

    def pooled(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of every run: sums of log-probabilities over its bytes, and bytes won, for each label (labels x runs)."""
        found = self.log_probabilities(x)
        won = found == found.max(1, keepdims=True)
        if (x == NONE).any():
            there = (x < NONE)[:, None]
            found, won = found * there, won & there
        return found.sum(0), won.sum(0)

    def fit(self, x: np.ndarray, y: np.ndarray, seed: int = 7) -> None:
        """x: runs x time, y: labels of runs. Adam on the cross-entropy of every position."""
        rng = np.random.default_rng(seed)
        params = [getattr(self, k) for k in self.PARTS]
        moment, square, step = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
        total = EPOCHS * max(1, len(x) // BATCH)
        for _ in range(EPOCHS):
            order = rng.permutation(len(x))
            for i in range(0, max(1, len(x) - BATCH + 1), BATCH):
                take = order[i : i + BATCH]
                length = int((x[take] < NONE).sum(1).max())
                grads = self._gradients(np.ascontiguousarray(x[take, :length].T), y[take])
                step += 1
                rate = np.float32(RATE * (1 - step / (total + 1)) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step))
                for p, m, s, g in zip(params, moment, square, grads, strict=True):
                    m += np.float32(0.1) * (g - m)
                    s += np.float32(0.001) * (g * g - s)
                    p -= rate * m / (np.sqrt(s) + np.float32(1e-8))

    def _gradients(self, x: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
        """Backpropagation through time, of the parts in their order."""
        (time, runs), n, e = x.shape, self.n, self.e
        mask, kept = (x < NONE).astype(np.float32), []
        states = self._states(x, mask, kept)
        p = self._logits(states)
        p = np.exp(p - p.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        p[:, y, np.arange(runs)] -= 1
        p *= (mask / max(1, mask.sum()))[:, None]
        ahead = (states[1:, 0, :n], states[:0:-1, 1, :n])
        grad_out = np.stack([np.tensordot(p, s, ((0, 2), (0, 2))) for s in ahead])
        from_out = [np.matmul(self.out[0].T, p), np.matmul(self.out[1].T, p)[::-1]]
        grad_gates, grad_given, grad_state = np.zeros_like(self.gates), np.zeros_like(self.given), np.zeros_like(self.state)
        grad_bytes, grad = np.zeros((time, e, runs), np.float32), np.zeros((2, n, runs), np.float32)
        turn = lambda m: m.transpose(0, 2, 1)
        for t in range(time - 1, -1, -1):
            gates, from_state, c = kept[t]
            z, r, before = gates[:, :n], gates[:, n:], states[t, :, :n]
            grad = grad + np.stack((from_out[0][t], from_out[1][t]))
            m = np.stack((mask[t], mask[time - 1 - t]))[:, None]
            moved = grad * m
            a_c = moved * z * (1 - c * c)
            through = a_c * r
            a = np.concatenate((moved * (c - before) * 2 * z * (1 - z), a_c * from_state * 2 * r * (1 - r)), 1)
            grad_gates += a @ turn(states[t])
            grad_given += a_c @ turn(states[t, :, n:])
            grad_state += through @ turn(before)
            below = turn(self.gates) @ a
            from_given = turn(self.given) @ a_c
            grad = grad * (1 - m * z) + turn(self.state) @ through + below[:, :n]
            own = below[:, n : n + e] + from_given[:, :e]
            grad_bytes[t] += own[0]
            grad_bytes[time - 1 - t] += own[1]
        grad_embed = np.zeros_like(self.embed)
        np.add.at(grad_embed, x.ravel(), grad_bytes.transpose(0, 2, 1).reshape(-1, e))
        return [grad_embed, grad_gates, grad_given, grad_state, grad_out, p.sum((0, 2))[:, None]]


def runs_of(offsets: np.ndarray, size: int = RUN) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, start and length of the runs of texts that begin and end at `offsets`."""
    length = np.diff(offsets)
    pieces = -(-length // size)
    doc = np.repeat(np.arange(len(length)), pieces)
    part = np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    start = offsets[doc] + part * size
    return doc, start, np.minimum(offsets[doc + 1] - start, size)


def matrix(data: np.ndarray, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The bytes of runs, one row each, NONE after the end."""
    places = np.arange(int(length.max(initial=0)))
    found = data[np.minimum(start[:, None] + places, len(data) - 1)].astype(np.int16) if len(data) else np.zeros((len(start), 0), np.int16)
    found[places >= length[:, None]] = NONE
    return found


def train(labelled: DataFrame, docs_each: int = TRAIN_DOCS, runs_each: int = TRAIN_RUNS, seed: int = 7) -> Network | None:
    """A network from rows of text and lang (nulls are left out); None if there are none.

    Of each language about `docs_each` documents, chosen by a hash of their text, are cut into runs, and at most `runs_each` of
    these, by a hash of theirs, are learned from, by one task. These bounds don't depend on the size of the table.
    """
    spark = labelled.sparkSession
    ship(spark)
    known = labelled.select("text", "lang").filter(F.col("lang").isNotNull() & (F.length("text") > 0))
    counts = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return None
    part = F.pmod(F.xxhash64("text", F.lit(seed)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chosen = F.coalesce(*(F.when(F.col("lang") == F.lit(k), part < F.lit(docs_each / n)) for k, n in counts.items()), F.lit(False))
    labels = sorted(counts)

    def cut(batches):
        for batch in batches:
            data, offsets = buffers(batch.column(0))
            doc, start, length = runs_of(offsets, TRAIN_BYTES)
            for i in range(0, len(doc), 10_000):
                own = slice(i, i + 10_000)
                yield pa.RecordBatch.from_arrays([batch.column(1).take(pa.array(doc[own])), pa.array([data[s : s + n].tobytes() for s, n in zip(start[own], length[own], strict=True)], pa.binary())], names=["lang", "run"])

    from pyspark.sql import Window

    turn = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("run", F.lit(seed)), "run"))
    runs = known.filter(chosen).mapInArrow(cut, "lang string, run binary").withColumn("turn", turn).filter(F.col("turn") <= runs_each)

    def learn(key, table):
        table = table.sort_by([("lang", "ascending"), ("turn", "ascending")])
        rows = table.column("run").to_pylist()
        length = np.array([len(r) for r in rows])
        x = matrix(np.frombuffer(b"".join(rows), np.uint8), np.cumsum(length) - length, length)
        network = Network(labels, seed)
        network.fit(x, np.searchsorted(np.array(labels), np.array(table.column("lang").to_pylist())), seed)
        return pa.table({"network": pa.array([network.dumped()], pa.binary())})

    made = runs.withColumn("all", F.lit(0)).select("all", "lang", "run", "turn").groupBy("all").applyInArrow(learn, "network binary").collect()
    return Network.loaded(bytes(made[0]["network"])) if made else Network(labels, seed)


_ASCII = re.compile(rb"[A-Za-z]")


def has_letter(text: bytes) -> bool:
    """Whether a text has a letter (Unicode categories L*)."""
    return bool(_ASCII.search(text)) or (not text.isascii() and any(c.isalpha() for c in text.decode("utf-8", "replace")))


def identify(docs: DataFrame, network: Network | None) -> DataFrame:
    """Adds lang_pred, score (its pooled probability) and parts (bytes labelled with each language) to `docs`, which needs text.

    A null text or one without any letter is "und" with score 0, as is every text where nothing was learned. Other columns
    stay; those of the three names are replaced. An empty table gives an empty result.
    """
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(network.dumped() if network else None)

    def make():
        net = Network.loaded(sent.value) if sent.value else None

        def work(batch):
            column = batch.column(batch.schema.get_field_index("text"))
            n, k = batch.num_rows, len(net.labels) if net else 0
            if not k:
                return {"lang_pred": [UNKNOWN] * n, "score": [0.0] * n, "parts": [[]] * n}
            total, votes = np.zeros((k, n)), np.zeros((k, n), np.int64)
            data, offsets = buffers(column)
            doc, start, length = runs_of(offsets)
            size = np.diff(offsets)
            per = max(TOGETHER, STEP // RUN)
            for i in range(0, len(doc), per):
                own = i + np.argsort(-length[i : i + per], kind="stable")
                for j in range(0, len(own), TOGETHER):
                    some = own[j : j + TOGETHER]
                    sums, wins = net.pooled(np.ascontiguousarray(matrix(data, start[some], length[some]).T))
                    for label in range(k):
                        total[label] += np.bincount(doc[some], sums[label], n)
                        votes[label] += np.bincount(doc[some], wins[label], n).astype(np.int64)
            mean = total / np.maximum(size, 1)
            mean = np.exp(mean - mean.max(0))
            mean /= mean.sum(0)
            best = mean.argmax(0)
            known = [has_letter(data[offsets[i] : offsets[i + 1]].tobytes()) for i in range(n)]
            return {
                "lang_pred": [net.labels[b] if ok else UNKNOWN for b, ok in zip(best, known, strict=True)],
                "score": [float(mean[b, i]) if ok else 0.0 for i, (b, ok) in enumerate(zip(best, known, strict=True))],
                "parts": [[{"lang": net.labels[j], "n_bytes": int(votes[j, i])} for j in np.flatnonzero(votes[:, i])] for i in range(n)],
            }

        return work

    return add_columns(docs, "lang_pred string, score double, parts array<struct<lang:string,n_bytes:long>>", make)


def held_out(id_column: str, modulus: int, remainder: int):
    """Whether crc32 of the id as text has this remainder; a null id counts as "null"."""
    return F.crc32(F.coalesce(F.col(id_column).cast("string"), F.lit("null")).cast("binary")) % modulus == remainder


def keep_known(docs: DataFrame, least: float = 0.0) -> DataFrame:
    """The documents whose language is found (with a score of at least `least`), with the columns they came with."""
    network = train(docs.filter(~held_out("doc_id", 3, 1)))
    found = identify(docs, network).filter((F.col("lang_pred") != UNKNOWN) & (F.col("score") >= least))
    return found.select(*docs.columns)


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang").withColumn("held_out", held_out("doc_id", 3, 1))
    network = train(docs.filter("NOT held_out"))
    return identify(docs.select("doc_id", "held_out", "text"), network).select("doc_id", "held_out", "lang_pred", "score")
