"""Token counts by Viterbi without the tokens.

An Aho-Corasick automaton over the bytes of a unigram vocabulary reports, at each position,
every piece that ends there. Dynamic programming keeps the best score and the number of
pieces behind it, nothing else. Words cannot share a piece (a metaspace stands only at the
start of pieces), so each distinct word is counted once and words are walked in lockstep, one
byte a step for thousands of words.

Ties are broken as the tokenizers library does: a path replaces another only if its score is
strictly higher, candidates coming in the order of their starts; a character with no piece of
its own gets the unknown score (lowest score less 10). Unknown characters count one token
for each byte with byte fallback, else one for each run of them.

Defined results: a null text is empty; an empty text has 0 tokens; repeated rows are counted
each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.llm.common import documents
from exactrank.llm.sentence_pieces import METASPACE, read_model

UNKNOWN_BELOW = 10.0
#: Bytes of distinct words that a worker remembers at most.
REMEMBERED = 40_000_000


@dataclass
class Automaton:
    """Dense transitions; ``ends[state]`` is the piece that ends here or -1, ``shorter`` the
    next state along suffix links where one ends (0 for none)."""

    step: np.ndarray
    ends: np.ndarray
    shorter: np.ndarray
    columns: np.ndarray
    lengths: np.ndarray
    scores: np.ndarray
    unknown: float
    byte_fallback: bool


def build_automaton(pieces: Sequence[tuple[str, float]], byte_fallback: bool) -> Automaton:
    raw = [p.encode() for p, _ in pieces]
    columns = np.zeros(256, np.int64)
    used = sorted({b for r in raw for b in r})
    columns[used] = np.arange(1, len(used) + 1)
    children: list[dict[int, int]] = [{}]
    depth, ends = [0], [-1]
    for i, r in enumerate(raw):
        at = 0
        for b in r:
            nxt = children[at].get(b)
            if nxt is None:
                nxt = children[at][b] = len(children)
                children.append({})
                depth.append(depth[at] + 1)
                ends.append(-1)
            at = nxt
        if at and ends[at] < 0:
            ends[at] = i
    n = len(children)
    step = np.zeros((n, len(used) + 1), np.int32)
    fail = np.zeros(n, np.int64)
    ends_at, shorter = np.array(ends), np.zeros(n, np.int64)
    parent, byte = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for s, kids in enumerate(children):
        for b, c in kids.items():
            parent[c], byte[c] = s, columns[b]
    by_depth = np.argsort(depth, kind="stable")
    levels = np.searchsorted(np.array(depth)[by_depth], np.arange(1, max(depth) + 2))
    for b, c in children[0].items():
        step[0, columns[b]] = c
    # A state starts as its suffix's row, then gets its own children; suffixes are less deep.
    for lo, hi in zip(levels[:-1], levels[1:]):
        own = by_depth[lo:hi]
        deep = own[parent[own] > 0]
        fail[deep] = step[fail[parent[deep]], byte[deep]]
        shorter[own] = np.where(ends_at[fail[own]] >= 0, fail[own], shorter[fail[own]])
        step[own] = step[fail[own]]
        for s in own:
            for b, c in children[s].items():
                step[s, columns[b]] = c
    scores = np.array([s for _, s in pieces])
    return Automaton(step, ends_at, shorter, columns, np.array([len(r) for r in raw]), scores, float(scores.min()) - UNKNOWN_BELOW, byte_fallback)


def viterbi_counts(words: Sequence[bytes], auto: Automaton) -> np.ndarray:
    """Pieces on the best path of each word. All words step together, longest first."""
    n = len(words)
    size = np.fromiter(map(len, words), np.int64, n)
    order = np.argsort(-size, kind="stable")
    size = size[order]
    if not n or not size[0]:
        return np.zeros(n, np.int64)
    width = int(size[0])
    flat = np.frombuffer(b"".join(words[i] for i in order), np.uint8)
    starts = np.concatenate([[0], np.cumsum(size)[:-1]])
    alive = np.searchsorted(-size, -np.arange(width), "left")  # words longer than t
    best = np.full((width + 1, n), -np.inf)
    best[0] = 0
    count = np.zeros((width + 1, n), np.int32)
    fused = np.zeros((width + 1, n), bool)  # the best path ends in an unknown character
    state = np.zeros(n, np.int64)
    char_from = np.zeros(n, np.int64)
    for t in range(width):
        m = alive[t]
        byte = flat[starts[:m] + t]
        fresh = (byte & 0xC0) != 0x80
        char_from[:m][fresh] = t
        state[:m] = auto.step[state[:m], auto.columns[byte]]
        at = state[:m]
        has_single = np.zeros(m, bool)
        own_char = t + 1 - char_from[:m]
        which = np.arange(m)
        at = np.where(auto.ends[at] >= 0, at, auto.shorter[at])
        # Suffix links go from the longest piece, which starts first, to the shortest.
        while True:
            live = at > 0
            which, at = which[live], at[live]
            if not len(which):
                break
            piece = auto.ends[at]
            begin = t + 1 - auto.lengths[piece]
            total = best[begin, which] + auto.scores[piece]
            better = total > best[t + 1, which]
            w = which[better]
            best[t + 1, w] = total[better]
            count[t + 1, w] = count[begin[better], w] + 1
            fused[t + 1, w] = False
            has_single[which] |= auto.lengths[piece] == own_char[which]
            at = auto.shorter[at]
        # At the last byte of a character without a piece of its own: the unknown candidate.
        last = np.ones(m, bool)
        more = np.flatnonzero(size[:m] > t + 1)
        last[more] = (flat[starts[more] + t + 1] & 0xC0) != 0x80
        w = np.flatnonzero(last & ~has_single)
        if len(w):
            begin = char_from[w]
            total = best[begin, w] + auto.unknown
            better = total > best[t + 1, w]
            w, begin = w[better], begin[better]
            best[t + 1, w] = total[better]
            new = (t + 1 - begin) if auto.byte_fallback else np.where(fused[begin, w], 0, 1)
            count[t + 1, w] = count[begin, w] + new
            fused[t + 1, w] = True
    out = np.zeros(n, np.int64)
    out[order] = count[size, np.arange(n)]
    return out


class WordCounter:
    """Token counts of whole texts, remembering counts of distinct words within a bound."""

    def __init__(self, pieces: Sequence[tuple[str, float]], byte_fallback: bool, remembered: int = REMEMBERED):
        if any(METASPACE in p.lstrip(METASPACE) for p, _ in pieces):
            raise ValueError("a piece holds a metaspace after other characters")
        self.auto = build_automaton(pieces, byte_fallback)
        self.known: dict[str, int] = {}
        self.size, self.limit = 0, remembered
        # Without byte fallback a run of unknown characters may cross words only if the metaspace is unknown.
        self.runs = any(p.count(METASPACE) > 1 for p, _ in pieces)

    def _learn(self, fresh: list[str]) -> None:
        raw = [w.encode() for w in fresh]
        by = sorted(range(len(raw)), key=lambda i: len(raw[i]))
        lo = 0
        while lo < len(by):
            # Bounded tables: words of like length, about four million cells at a time.
            hi, width = lo, 1
            while hi < len(by) and (hi - lo + 1) * (len(raw[by[hi]]) + 1) <= 4_000_000 or hi == lo:
                hi += 1
            part = by[lo:hi]
            for i, c in zip(part, viterbi_counts([raw[i] for i in part], self.auto)):
                self.known[fresh[i]] = int(c)
                self.size += len(raw[i]) + 100
            lo = hi

    def __call__(self, texts: Sequence[str]) -> list[int]:
        split = [words_with_marker(t) for t in texts]
        if self.size > self.limit:
            self.known.clear()
            self.size = 0
        fresh = {w for s in split for w in s if w not in self.known}
        self._learn(sorted(fresh))
        known = self.known
        return [sum([known[w] for w in s]) for s in split]


def words_with_marker(text: str) -> list[str]:
    """A text with spaces as metaspaces and one in front, cut before each run of them."""
    if not text:
        return []
    marked = text.replace(" ", METASPACE)
    if METASPACE * 2 not in marked and marked[0] != METASPACE and marked[-1] != METASPACE:
        return [METASPACE + w for w in marked.split(METASPACE)]
    out, run = [], METASPACE
    for w in marked.split(METASPACE)[0:]:
        if w:
            out.append(run + w)
            run = METASPACE
        else:
            run += METASPACE
    if len(run) > 1:
        out.append(run[1:])
    return out


_counters: dict[str, WordCounter] = {}


def count_tokens(docs: DataFrame, model: str) -> DataFrame:
    """doc_id, n_tokens, n_words (runs between spaces) of each text of ``docs(doc_id, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if model not in _counters:
            m = read_model(model)
            _counters[model] = WordCounter(m.unigram_vocabulary(), m.byte_fallback)
        for batch in batches:
            texts = [t or "" for t in batch["text"].to_pylist()]
            counts: list[int] = []
            for at in range(0, len(texts), 512):
                counts += _counters[model](texts[at : at + 512])
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array([len(t) for t in texts], pa.int64()), pa.array(counts, pa.int64())], ["doc_id", "n_chars", "n_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_chars long, n_tokens long")


def op9_unigram_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return count_tokens(documents(spark, sf_dir, "doc_id", "text"), public_tokenizers.path("piece_bpe_32k.model"))
