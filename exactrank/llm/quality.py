"""Quality rules: counted rules beside a hashed n-gram classifier.

The classifier is a logistic regression on hashed words, word pairs and 3- and 4-grams of code
points (each as a share of its kind), fitted on labelled quality rows, its scores calibrated on rows kept apart,
and applied in Arrow batches against a fixed threshold. Training reads at most ``FIT_ROWS``
labelled documents (those of smallest id hash, the same in each run); scoring reads all.

Defined results: a null or wordless text has all counts 0 and fails the base rule of 10
words; repeated rows get equal results; with no labelled rows, or labels of one kind, the
verdict is the base rules' alone; an empty table gives no rows; extra columns are carried
by ``keep_good`` and ignored by the query.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.llm.chunks import release_memory
from exactrank.llm.common import documents
from exactrank.llm.textkernel import IN_WORD, SpanHash, in_window, mix, ngram_hash, owner, per_text, pieces, text_buffer, word_bounds

#: Labelled documents that the classifier is fitted on at most (a fifth of them calibrates).
FIT_ROWS = 3000
BITS = 18
#: Features that the fit works on at a time.
FIT_BLOCK = 250_000
#: A document is kept from this calibrated probability of good quality on.
THRESHOLD = 0.5
WINDOW = 5
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_LEADS = (np.arange(256) & 0xC0) != 0x80
_SHIFT = np.uint64(64 - BITS)


@dataclass(frozen=True)
class Verdict:
    """Weights by hashed feature, for a linear score and its calibration."""

    weights: np.ndarray
    bias: float
    slope: float
    offset: float

    def probability(self, score: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * (score + self.bias) + self.offset, -40, 40)))


def code_points(data: np.ndarray) -> np.ndarray:
    """The code points of valid UTF-8 bytes."""
    if not len(data) or data.max() < 0x80:
        return data.astype(np.uint64)
    at = np.flatnonzero(_LEADS[data])
    first = data[at].astype(np.uint64)
    size = np.diff(np.append(at, len(data)))
    point = np.where(size > 1, first & ((np.uint64(1) << (np.uint64(7) - size.astype(np.uint64).clip(max=4))) - np.uint64(1)), first)
    for i in range(1, 4):
        more = size > i
        point[more] = (point[more] << np.uint64(6)) | (data[at[more] + i] & 0x3F)
    return point


def features(data: np.ndarray, offs: np.ndarray, spans: SpanHash, bounds) -> list[tuple[np.ndarray, np.ndarray]]:
    """(hashed feature, text) of every occurrence, one pair of arrays for each kind: words, pairs
    of neighbouring words, 3- and 4-grams of code points."""
    starts, ends, cuts = bounds
    words, rows = spans(starts, ends), owner(cuts)
    found = [((mix(words) >> _SHIFT).astype(np.int64), rows)]
    inside = in_window(rows, 2)
    found.append(((mix(ngram_hash(words, 2) + np.uint64(0x9216D5D9)) >> _SHIFT).astype(np.int64)[inside], rows[: len(inside)][inside]))
    points = code_points(data)
    before = np.concatenate([[0], np.cumsum(_LEADS[data])])
    rows = owner(before[offs])
    for n, seed in ((3, 0x51ED270B), (4, 0x2545F491)):
        m = len(points) - n + 1
        if m <= 0:
            found.append((np.zeros(0, np.int64), np.zeros(0, np.int64)))
            continue
        gram = np.full(m, seed, np.uint64)
        for i in range(n):
            gram = gram * np.uint64(0x9E3779B97F4A7C15) + points[i : i + m]
        inside = in_window(rows, n)
        found.append(((mix(gram) >> _SHIFT).astype(np.int64)[inside], rows[:m][inside]))
    return found


def linear_scores(weights: np.ndarray, kinds, n: int) -> np.ndarray:
    total = np.zeros(n)
    for ids, rows in kinds:
        size = np.maximum(np.bincount(rows, minlength=n), 1)
        total += np.bincount(rows, weights=weights[ids], minlength=n) / size
    return total


def rule_counts(data: np.ndarray, offs: np.ndarray, spans: SpanHash, bounds) -> dict[str, np.ndarray]:
    starts, ends, cuts = bounds
    n = len(offs) - 1
    newlines = np.flatnonzero(data == 10)
    line_from = np.sort(np.concatenate([offs[:-1], newlines + 1]))
    line_to = np.sort(np.concatenate([newlines, offs[1:]]))
    worded = np.searchsorted(starts, line_to) > np.searchsorted(starts, line_from)
    line_from, line_to = line_from[worded], line_to[worded]
    line_row = np.searchsorted(offs, line_from, "right") - 1
    line_hash = spans(line_from, line_to)
    order = np.lexsort((line_hash, line_row))
    h, r = line_hash[order], line_row[order]
    again = (h[1:] == h[:-1]) & (r[1:] == r[:-1])

    rows = owner(cuts)
    grams = ngram_hash(spans(starts, ends), WINDOW)
    inside = np.flatnonzero(in_window(rows, WINDOW))
    key = mix(grams[inside] + rows[inside].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    order = np.argsort(key)
    same = key[order][1:] == key[order][:-1]
    twice = np.zeros(len(inside), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(len(starts) + 1, np.int64)
    np.add.at(edge, inside[twice], 1)
    np.add.at(edge, inside[twice] + WINDOW, -1)
    covered = np.cumsum(edge[:-1]) > 0
    return {
        "n_words": np.diff(cuts),
        "word_chars": per_text(IN_WORD[data] & _LEADS[data], offs),
        "n_symbols": per_text(_SYMBOL[data], offs),
        "n_dup_lines": np.bincount(r[1:][again], minlength=n),
        "n_repeat_words": per_text(covered, cuts),
    }


def assess(texts: pa.Array, verdict: Verdict | None, threshold: float = THRESHOLD) -> dict[str, np.ndarray]:
    data, offs = text_buffer(texts)
    parts = []
    for _, _, part, cut in pieces(data, offs):
        spans, bounds = SpanHash(part), word_bounds(part, cut)
        out = rule_counts(part, cut, spans, bounds)
        out["base_failed"] = (out["n_words"] < MIN_WORDS) | (100 * out["n_repeat_words"] > MAX_REPEAT_PERCENT * out["n_words"])
        if verdict is None:
            out["probability"] = np.ones(len(cut) - 1)
        else:
            out["probability"] = verdict.probability(linear_scores(verdict.weights, features(part, cut, spans, bounds), len(cut) - 1))
        out["kept"] = ~out["base_failed"] & (out["probability"] >= threshold)
        parts.append(out)
    return {k: np.concatenate([p[k] for p in parts]) for k in parts[0]} if parts else {}


def _sample_features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offs = text_buffer(batch["text"])
        ids, shares = [], []
        for _, _, part, cut in pieces(data, offs):
            n = len(cut) - 1
            kinds = features(part, cut, SpanHash(part), word_bounds(part, cut))
            each = [(f, r, 1 / np.maximum(np.bincount(r, minlength=n), 1)[r]) for f, r in kinds]
            f, r, v = (np.concatenate(x) for x in zip(*each))
            key, back = np.unique(r * (1 << BITS) + f, return_inverse=True)
            total = np.bincount(back, weights=v, minlength=len(key))
            cuts = np.searchsorted(key, np.arange(n + 1) << BITS)
            for i in range(n):
                ids.append((key[cuts[i] : cuts[i + 1]] & ((1 << BITS) - 1)).astype(np.int32).tobytes())
                shares.append(total[cuts[i] : cuts[i + 1]].astype(np.float32).tobytes())
        yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["quality"], pa.array(ids, pa.binary()), pa.array(shares, pa.binary())], ["doc_id", "quality", "ids", "shares"])


def fit(rows: list, epochs: int = 60, rate: float = 0.15, decay: float = 1e-6) -> Verdict | None:
    """Logistic regression by full-batch adaptive gradient steps, then two calibration numbers
    fitted on every fifth row, which the weights have not seen."""
    rows = sorted(rows, key=lambda r: (r["doc_id"], r["quality"]))
    y = np.array([r["quality"] > 0 for r in rows], float)
    if not len(y) or y.min() == y.max():
        return None
    apart = np.arange(len(rows)) % 5 == 4

    def blocks(which: np.ndarray) -> list[tuple]:
        """(ids, shares, rows) of some rows at a time, so that the working arrays stay small."""
        own, out, at = [rows[i] for i in np.flatnonzero(which)], [], 0
        while at < len(own):
            to, size = at, 0
            while to < len(own) and (to == at or size < FIT_BLOCK):
                size += len(own[to]["ids"]) // 4
                to += 1
            ids = [np.frombuffer(r["ids"], np.int32) for r in own[at:to]]
            row = np.repeat(np.arange(at, to, dtype=np.int32), [len(i) for i in ids])
            out.append((np.concatenate(ids), np.concatenate([np.frombuffer(r["shares"], np.float32) for r in own[at:to]]), row))
            at = to
        return out

    def linear(parts: list[tuple], n: int) -> np.ndarray:
        z = np.full(n, b)
        for ids, v, row in parts:
            z += np.bincount(row, weights=w[ids] * v, minlength=n)
        return z

    w, b, seen, seen_b = np.zeros(1 << BITS), 0.0, np.full(1 << BITS, 1e-8), 1e-8
    parts, target = blocks(~apart), y[~apart]
    n = len(target)
    # Both kinds weigh alike, however rare one is.
    weigh = np.where(target > 0, 0.5 / max(target.mean(), 1e-9), 0.5 / max(1 - target.mean(), 1e-9))
    for _ in range(epochs):
        g = weigh * (1 / (1 + np.exp(-np.clip(linear(parts, n), -40, 40))) - target) / n
        gw = decay * w
        for ids, v, row in parts:
            gw += np.bincount(ids, weights=g[row] * v, minlength=1 << BITS)
        gb = g.sum()
        seen += gw * gw
        seen_b += gb * gb
        w -= rate * 20 * gw / np.sqrt(seen)
        b -= rate * gb / np.sqrt(seen_b)
    parts, held = (blocks(apart), y[apart]) if apart.any() else (parts, target)
    n = len(held)
    z = linear(parts, n)
    scale = max(np.abs(z).mean(), 1e-9)
    # Newton steps on (slope, offset); targets are smoothed so that separable scores stay finite.
    up, down = held.sum(), len(held) - held.sum()
    smooth = np.where(held > 0, (up + 1) / (up + 2), 1 / (down + 2))
    x = np.stack([z / scale, np.ones(n)], 1)
    theta = np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ theta, -40, 40)))
        hess = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        theta -= np.linalg.solve(hess, x.T @ (p - smooth) + 1e-3 * (theta - [1.0, 0.0]))
    return Verdict(w.astype(np.float32), float(b), float(theta[0] / scale), float(theta[1]))


def _fit_table(table: pa.Table) -> pa.Table:
    verdict = fit(table.to_pylist())
    del table
    release_memory()
    rows = [] if verdict is None else [(verdict.weights.tobytes(), verdict.bias, verdict.slope, verdict.offset)]
    columns = list(zip(*rows)) or [()] * 4
    return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.binary(), *[pa.float64()] * 3))], ["weights", "bias", "slope", "offset"])


def train(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> Verdict | None:
    """Fit on at most ``fit_rows`` labelled documents: that many ids are broadcast, that many
    feature rows go to one task, and its weights (a fixed size) come to the driver."""
    chosen = (
        labels.where("quality IS NOT NULL AND doc_id IS NOT NULL")
        .groupBy("doc_id").agg(F.max("quality").alias("quality"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(fit_rows)
    )
    # Repeated ids could bring more rows than labels: the least text of each is taken.
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.min("text").alias("text"))
    rows = sample.select("doc_id", "quality", "text").mapInArrow(_sample_features, "doc_id long, quality int, ids binary, shares binary")
    found = rows.groupBy(F.lit(0).alias("all")).applyInArrow(_fit_table, "weights binary, bias double, slope double, offset double").collect()
    return Verdict(np.frombuffer(bytes(found[0]["weights"]), np.float32), found[0]["bias"], found[0]["slope"], found[0]["offset"]) if found else None


_COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def assess_quality(docs: DataFrame, verdict: Verdict | None, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, the counts, base_failed, probability, kept: one row per row, no exchange."""
    shared = docs.sparkSession.sparkContext.broadcast(verdict)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                out = assess(batch["text"], shared.value, threshold)
                names = [*_COUNTS, "base_failed", "probability", "kept"]
                yield pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array(out[k]) for k in names)], ["doc_id", *names])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
        run, "doc_id long, " + ", ".join(f"{c} long" for c in _COUNTS) + ", base_failed boolean, probability double, kept boolean"
    )


def keep_good(docs: DataFrame, verdict: Verdict | None, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` (all columns) that pass, streamed through without an exchange."""
    shared = docs.sparkSession.sparkContext.broadcast(verdict)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield batch.filter(pa.array(assess(batch["text"], shared.value, threshold)["kept"]))

    return docs.mapInArrow(run, docs.schema)


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir, "doc_id", "text")
    verdict = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return assess_quality(docs, verdict)
