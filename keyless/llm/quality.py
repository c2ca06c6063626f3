"""Quality rules from the repeated substrings of each text.

A sparse suffix array over words is built for every document: a repeated substring of ``seed`` words or more can begin
only where a repeated window of ``seed`` words stands, so only those positions are sorted, by prefix doubling.  Neighbours
in suffix order give the longest-common-prefix intervals; the union of their spans is the covered part of the text.

Defined cases: null or empty text has no words, so the base rule rejects it; documents never share suffixes; repeated rows
and repeated or null ids are separate documents; other columns pass through ``keep_clean`` unchanged.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless.llm import kernels as K
from keyless.llm.workspace import ship, table

U = np.uint64


@dataclass(frozen=True)
class Limits:
    """A text is rejected with fewer words than ``least_words``, more than ``repeat_percent`` of words in repeated three-word
    windows, more than ``covered`` of its words inside repeats of ``min_repeat`` words, or one repeat above ``longest`` words."""

    least_words: int = 50
    repeat_percent: int = 50
    min_repeat: int = 8
    covered: float = 0.4
    longest: int = 300


SCHEMA = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, covered_words long, longest_repeat long, base_failed boolean, kept boolean"
_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True


def _repeated(key: np.ndarray) -> np.ndarray:
    """Which entries have an equal one elsewhere."""
    order = np.argsort(key, kind="stable")
    k = key[order]
    same = np.zeros(len(k) + 1, bool)
    same[1:-1] = k[1:] == k[:-1]
    out = np.zeros(len(k), bool)
    out[order] = same[:-1] | same[1:]
    return out


def repeats(w: np.ndarray, doc: np.ndarray, bounds: np.ndarray, seed: int, flagged: np.ndarray, window: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(position, length in words) of the longest repeat that begins at each flagged position.

    ``window``: hash of the ``seed`` words at each position with its document; ``flagged``: where that window repeats."""
    pos = np.flatnonzero(flagged)
    if not len(pos):
        return pos, pos
    # the rank of a position is the place where its group begins in suffix order, so a group splits within its own places
    rank = np.full(len(w) + 1, -1, np.int64)
    _, back, size = np.unique(window[pos], return_inverse=True, return_counts=True)
    rank[pos] = (np.cumsum(size) - size)[back]
    end = bounds[doc + 1]
    padded = np.concatenate([w, np.zeros(2, np.uint64)])
    live, h = pos, seed
    while len(live):
        nxt = np.minimum(live + h, len(w))
        left = end[live] - live - h
        one = np.where(left > 0, padded[nxt], U(0))
        two = np.where(left > 1, padded[np.minimum(nxt + 1, len(w))], U(0))
        # a follower whose window does not repeat is unlike any other
        follow = np.where((left > 0) & (rank[nxt] >= 0), rank[nxt], -2 - live)
        group = rank[live]
        order = np.lexsort((follow, two, one, group))
        group, follow = group[order], follow[order]
        new = np.ones(len(group), bool)
        new[1:] = (group[1:] != group[:-1]) | (follow[1:] != follow[:-1])
        place = np.arange(len(group))
        begun = np.maximum.accumulate(np.where(np.r_[True, group[1:] != group[:-1]], place, 0))
        rank[live[order]] = group + np.maximum.accumulate(np.where(new, place, 0)) - begun
        size = np.diff(np.r_[np.flatnonzero(new), len(group)])
        live = live[order][np.repeat(size > 1, size)]
        h *= 2
    order = np.argsort(rank[pos], kind="stable")
    sa = pos[order]
    # exact common prefixes of neighbours by bisection over word hashes
    hw = np.zeros(len(w) + 1, np.uint64)
    pw, inv = K.powers(len(w) + 1)
    np.cumsum(K.mix(w) * pw[: len(w)], out=hw[1:])
    x, y = sa[:-1], sa[1:]
    lo = np.zeros(len(x), np.int64)
    hi = np.where(doc[x] == doc[y], np.minimum(end[x] - x, end[y] - y), 0)
    while len(x) and (lo < hi).any():
        mid = (lo + hi + 1) // 2
        same = (hw[x + mid] - hw[x]) * inv[x] == (hw[y + mid] - hw[y]) * inv[y]
        lo, hi = np.where(same, mid, lo), np.where(same, hi, mid - 1)
    best = np.zeros(len(sa), np.int64)
    if len(x):
        best[:-1] = lo
        best[1:] = np.maximum(best[1:], lo)
    return sa, best


def measure(buf: np.ndarray, offs: np.ndarray, limits: Limits) -> dict[str, np.ndarray]:
    n = len(offs) - 1
    s, e, doc, bounds = K.words(buf, offs)
    n_words = np.diff(bounds)
    h = K.prefix_hash(buf)
    space = np.zeros(len(buf) + 1, np.int64)
    inside = ~K._SPACE[buf]
    np.cumsum(inside & ((buf & 0xC0) != 0x80), out=space[1:])
    chars = space[offs[1:]] - space[offs[:-1]]
    symbols = K.per_document(_SYMBOL[buf], offs)
    # lines: between the offsets and the line feeds
    feeds = np.flatnonzero(buf == 10)
    ls = np.unique(np.concatenate([offs[:-1], feeds + 1]))
    line_doc = np.searchsorted(offs, ls, side="right") - 1
    ok = line_doc < n
    ls, line_doc = ls[ok], line_doc[ok]
    nxt = np.searchsorted(feeds, ls)
    le = np.minimum(np.where(nxt < len(feeds), feeds[np.minimum(nxt, len(feeds) - 1)] if len(feeds) else 0, len(buf)), offs[line_doc + 1])
    le = np.where(nxt < len(feeds), le, offs[line_doc + 1])
    full = space[le] > space[ls]
    ls, le, line_doc = ls[full], le[full], line_doc[full]
    salt = K.mix(np.arange(1, n + 1, dtype=np.uint64) * U(0xDB4F0B9175AE2165))
    key = K.span_hash(h, ls, le) ^ salt[line_doc]
    _, first = np.unique(key, return_index=True)
    dup = np.bincount(line_doc, minlength=n) - np.bincount(line_doc[first], minlength=n)
    w = K.span_hash(h, s, e)
    m = max(len(w) - 2, 0)
    tri = K.mix(K.mix(K.mix(w[:m]) + w[1 : m + 1]) + w[2 : m + 2]) ^ salt[doc[:m]]
    valid = np.zeros(len(w), bool)
    valid[:m] = doc[:m] == doc[2 : m + 2]
    at = np.flatnonzero(valid)
    flagged = np.zeros(len(w), bool)
    flagged[at] = _repeated(tri[at])
    covered3 = flagged.copy()
    covered3[1:] |= flagged[:-1]
    covered3[2:] |= flagged[:-2]
    window = np.zeros(len(w), np.uint64)
    window[:m] = tri
    sa, best = repeats(w, doc, bounds, 3, flagged, window)
    use = best >= limits.min_repeat
    depth = np.zeros(len(w) + 1, np.int64)
    np.add.at(depth, sa[use], 1)
    np.add.at(depth, sa[use] + best[use], -1)
    covered = np.cumsum(depth[:-1]) > 0
    longest = np.zeros(n, np.int64)
    np.maximum.at(longest, doc[sa], best)
    out = {"n_words": n_words, "word_chars": chars, "n_symbols": symbols, "n_dup_lines": dup, "n_repeat_words": K.per_document(covered3, bounds), "covered_words": K.per_document(covered, bounds), "longest_repeat": longest}
    out["base_failed"] = (n_words < limits.least_words) | (100 * out["n_repeat_words"] > limits.repeat_percent * n_words)
    out["kept"] = ~(out["base_failed"] | (out["covered_words"] > limits.covered * n_words) | (longest > limits.longest))
    return out


def judge(docs: DataFrame, limits: Limits = Limits(), text: str = "text") -> DataFrame:
    """All columns of ``docs`` but the clashing ones, followed by the measures and the verdict."""
    ship(docs.sparkSession)
    names = [x.split(" ")[0] for x in SCHEMA.split(", ")]
    clash = [c for c in docs.columns if c.lower() in names]
    docs = docs.drop(*clash)
    schema = f"{docs._jdf.schema().toDDL()}, {SCHEMA}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(batch.schema.get_field_index(text))
            for i, j, buf, offs in K.slabs(column):
                got = measure(buf, offs, limits)
                yield pa.RecordBatch.from_arrays([*batch.slice(i, j - i).columns, *[pa.array(got[c]) for c in names]], names=[*batch.schema.names, *names])

    return docs.mapInArrow(run, schema)


def keep_clean(docs: DataFrame, limits: Limits = Limits(), text: str = "text") -> DataFrame:
    """The rows of ``docs`` that pass, with their own columns only."""
    names = {x.split(" ")[0] for x in SCHEMA.split(", ")}
    own = {c: f"__own_{i}" for i, c in enumerate(docs.columns) if c.lower() in names}
    held = docs.withColumnsRenamed(own)
    return judge(held, limits, text).filter("kept").select(*[F.col(own.get(c, c)).alias(c) for c in docs.columns])


def op10_suffix_repetition(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "covered_words", "longest_repeat")
