"""Benchmark decontamination by Wu-Manber search over words.

A document word is hit if it lies inside any occurrence of a window of a test item; a
document is contaminated if at least a twentieth of its words are hit.

The searched symbols are words, as 64-bit numbers. All windows of one length form a class;
for a class the shift table tells, for the block of the last two words under the scan
position, how far the scan may jump because no window can end sooner; a jump of nothing
opens the bucket of that suffix block, a hash of the whole window picks the candidates in
it, and word-by-word comparison confirms.

The index is a few flat arrays, made once on the driver and broadcast: about 40 bytes for
each window. Test sets of more than BLOCK_WORDS words are searched in blocks, one pass over
the documents each. Many scans run side by side: each starts at its own place of a text.

Edge cases: a null or word-less text has 0 words and is clean; an item without words has
no window; items with a null id hit words but are neither counted nor listed; repeated
items and ids count once; with no items every document is clean; repeated rows and rows
with a null id are searched like others.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from .common import ALNUM, WordHasher, annotate, free_names, mix

WINDOW = 13
#: Words of test items that are indexed together (about 40 bytes each); larger test sets are searched in blocks.
BLOCK_WORDS = 4_000_000
#: Text of test items that is turned into words at once.
READ_BYTES = 1 << 20
#: Word places that one scan covers.
STRIDE = 512
#: Slots of a shift table for each block of words in it.
SLOTS = 4
_FACTOR = np.uint64(0x9E3779B97F4A7C15)


def _pairs(w: np.ndarray, block: int) -> np.ndarray:
    """The hash of the block that ends on each word (the first of a text has none of two words)."""
    if block == 1:
        return mix(w)
    out = mix(w)
    out[1:] = mix(mix(w[:-1]) * _FACTOR + w[1:])
    return out


def _whole(w: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
    """The hashes of the ``size`` words from each of ``starts`` on."""
    out = np.full(len(starts), size, np.uint64)
    for k in range(size):
        out = mix(out * _FACTOR + w[starts + k])
    return out


class WindowClass:
    """Windows of ``size`` words: ``words`` holds them all, ``starts`` where each begins, ``owner`` the item of each."""

    def __init__(self, size: int, words: np.ndarray, starts: np.ndarray, owner: np.ndarray):
        self.size, self.block, self.words = size, min(2, size), words
        pairs = _pairs(words, self.block)
        ends = starts + size - 1
        whole = _whole(words, starts, size)
        # one bucket key: half of the suffix block's hash, half of the window's
        key = self._key(pairs[ends], whole)
        order = np.lexsort((owner, whole, key))
        key, starts, owner = key[order], starts[order], owner[order]
        # equal windows are one, with the list of their items; windows that only share a key stay apart
        new = np.ones(len(key), bool)
        if len(key) > 1:
            new[1:] = (key[1:] != key[:-1]) | ~self._equal(words, starts[1:], words, starts[:-1])
        self.keys, self.starts = key[new], starts[new]
        first = np.flatnonzero(new)
        self.owners, self.bounds = owner.astype(np.int32), np.append(first, len(key)).astype(np.int64)
        width = 1 << max(4, int(SLOTS * max(1, len(self.starts)) - 1).bit_length())
        self.mask = np.uint64(width - 1)
        self.jump = size - self.block + 1
        self.shift = np.full(width, self.jump, np.uint8)
        for back in range(self.jump):  # from the block that ends a window to the one that begins it
            np.minimum.at(self.shift, (pairs[self.starts + size - 1 - back] & self.mask).astype(np.int64), np.uint8(back))

    @staticmethod
    def _key(suffix: np.ndarray, whole: np.ndarray) -> np.ndarray:
        return ((suffix >> np.uint64(32)) << np.uint64(32)) | (whole >> np.uint64(32))

    def _equal(self, a: np.ndarray, at: np.ndarray, b: np.ndarray, bt: np.ndarray) -> np.ndarray:
        same = np.ones(len(at), bool)
        for k in range(self.size):
            same &= a[at + k] == b[bt + k]
        return same

    def search(self, w: np.ndarray, pairs: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(last word, window) of all occurrences in texts whose words are w[bounds[i]:bounds[i + 1]]."""
        low, high = bounds[:-1] + self.size - 1, bounds[1:]
        low, high = low[low < high], high[low < high]
        pieces = -(-(high - low) // STRIDE)
        number = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        at = np.repeat(low, pieces) + number * STRIDE
        stop = np.minimum(at + STRIDE, np.repeat(high, pieces))
        ends = []
        while len(at):
            step = self.shift[(pairs[at] & self.mask).astype(np.int64)]
            ends.append(at[step == 0])
            at = at + np.maximum(step, 1)
            on = at < stop
            at, stop = at[on], stop[on]
        ends = np.concatenate(ends) if ends else np.zeros(0, np.int64)
        key = self._key(pairs[ends], _whole(w, ends - self.size + 1, self.size))
        where = np.searchsorted(self.keys, key)
        found_end, found = [], []
        while len(ends):  # nearly always once: windows that share a key follow each other
            on = where < len(self.keys)
            on[on] = self.keys[where[on]] == key[on]
            ends, where, key = ends[on], where[on], key[on]
            same = self._equal(w, ends - self.size + 1, self.words, self.starts[where])
            found_end.append(ends[same])
            found.append(where[same])
            ends, where, key = ends[~same], where[~same] + 1, key[~same]
        return (np.concatenate(found_end), np.concatenate(found)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64))


class WindowSearch:
    """Shift tables and suffix buckets over the windows of ``items`` (id, text as bytes)."""

    def __init__(self, items: Iterable[tuple[object, bytes | None]], width: int = WINDOW):
        hasher, parts, lengths, self.ids, held, size = WordHasher(ALNUM), [], [], [], [], 0

        def read():
            h, bounds = hasher(held)
            parts.append(h)
            lengths.append(np.diff(bounds))
            held.clear()

        for item_id, text in items:
            self.ids.append(None if item_id is None else str(item_id))
            held.append(text)
            size += len(text or b"")
            if size > READ_BYTES:
                read()
                size = 0
        read()
        words, n = np.concatenate(parts), np.concatenate(lengths)
        first = np.cumsum(n) - n
        sizes = np.minimum(n, width)
        self.classes = []
        for s in np.unique(sizes[sizes > 0]).tolist():
            own = np.flatnonzero(sizes == s)
            windows = n[own] - s + 1
            starts = np.repeat(first[own], windows) + np.arange(windows.sum()) - np.repeat(np.cumsum(windows) - windows, windows)
            self.classes.append(WindowClass(s, words, starts, np.repeat(own, windows)))

    def nbytes(self) -> int:
        arrays = [x for c in self.classes for x in (c.keys, c.starts, c.owners, c.bounds, c.shift)]
        return sum(x.nbytes for x in arrays) + (self.classes[0].words.nbytes if self.classes else 0)

    def __call__(self, w: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, list[set[str]]]:
        """Which words are hit, and the ids of the items found in each text."""
        edge = np.zeros(len(w) + 1, np.int64)
        ids: list[set[str]] = [set() for _ in bounds[1:]]
        pairs = {b: _pairs(w, b) for b in {c.block for c in self.classes}}
        for c in self.classes:
            ends, found = c.search(w, pairs[c.block], bounds)
            np.add.at(edge, ends - c.size + 1, 1)
            np.add.at(edge, ends + 1, -1)
            text = np.searchsorted(bounds, ends, side="right") - 1
            for t, k in {*zip(text.tolist(), found.tolist())}:
                ids[t].update(i for i in (self.ids[o] for o in c.owners[c.bounds[k] : c.bounds[k + 1]]) if i is not None)
        return np.cumsum(edge[:-1]) > 0, ids


def spans_of(hit: np.ndarray) -> list[dict]:
    """Ranges of hit words of one text."""
    edge = np.flatnonzero(np.diff(hit, prepend=False, append=False)).tolist()
    return [{"first": a, "past": b} for a, b in zip(edge[::2], edge[1::2])]


_SPANS = T.ArrayType(T.StructType([T.StructField("first", T.LongType()), T.StructField("past", T.LongType())]))


def _pass(docs: DataFrame, search: WindowSearch, text: str, keep: Sequence[str] | None) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(search)

    def start():
        search, hasher = held.value, WordHasher(ALNUM)

        def work(texts):
            w, bounds = hasher(texts)
            hit, ids = search(w, bounds)
            spans = [spans_of(hit[a:b]) if x else [] for a, b, x in zip(bounds, bounds[1:], np.diff(np.concatenate([[0], np.cumsum(hit)])[bounds]))]
            return np.diff(bounds).tolist(), spans, [sorted(x) for x in ids]

        return work

    return annotate(docs, [text], [("n_words", T.LongType()), ("spans", _SPANS), ("items", T.ArrayType(T.StringType()))], start, keep)


def contamination(
    docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text",
    width: int = WINDOW, share: int = 20, block_words: int = BLOCK_WORDS, keep: Sequence[str] | None = None,
) -> DataFrame:
    """Rows of ``docs`` with n_words, spans (hit word ranges), items (ids found), n_hit and contaminated.

    The test set is read in blocks of about ``block_words`` words: the index of each block is
    broadcast and searched for in one pass over the documents; the passes follow one
    another without a shuffle, and later ones add to the spans of earlier ones.
    """
    kept = list(docs.columns) if keep is None else list(keep)
    chosen = benchmark.select(F.col(item_id).alias("i"), F.col(item_text).cast("binary").alias("t")).where("t is not null").distinct()
    # a word and what parts it from the next take two bytes at least
    size = chosen.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    blocks = max(1, -(-size // (2 * block_words)))
    source = docs.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*kept, text])])
    out = source
    for b in range(blocks):
        part = chosen if blocks == 1 else chosen.where(F.pmod(F.xxhash64("i", "t"), F.lit(blocks)) == b)
        search = WindowSearch(((r.i, bytes(r.t)) for r in part.toLocalIterator()), width)
        had = list(out.columns)
        out = _pass(out, search, text, None)
        new = out.columns[len(had):]
        if b:
            n0, s0, i0 = before
            out = out.select(
                *[F.col(f"`{c}`") for c in source.columns],
                F.col(n0).alias(n0),
                F.concat(F.col(s0), F.col(new[1])).alias(s0),
                F.array_union(F.col(i0), F.col(new[2])).alias(i0),
            )
        else:
            before = new
    n, s, i = before
    # positions of spans from several blocks may overlap: join those that touch
    if blocks > 1:
        def absorb(acc, x):
            last = F.element_at(acc, -1)
            return (
                F.when(F.size(acc) == 0, F.array(x))
                .when(x["first"] <= last["past"], F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(last["first"].alias("first"), F.greatest(last["past"], x["past"]).alias("past")))))
                .otherwise(F.concat(acc, F.array(x)))
            )

        out = out.withColumn(s, F.aggregate(F.array_sort(s), F.slice(F.col(s), 1, 0), absorb)).withColumn(i, F.array_sort(i))
    hit, bad = free_names(["n_hit", "contaminated"], out.columns)
    n_hit = F.aggregate(F.col(s), F.lit(0).cast("long"), lambda a, x: a + x["past"] - x["first"])
    out = out.withColumn(hit, n_hit).withColumn(bad, (F.col(hit) > 0) & (F.col(hit) * share >= F.col(n)))
    return out if text in kept else out.drop(text)


def op1_decontamination(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    tests = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    found = contamination(docs.select("doc_id", "text"), tests.select("item_id", "text"), keep=["doc_id"])
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), "contaminated",
    )


OP1_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark
), bi AS (
  SELECT item_id, w, least(13, len(w)) AS m, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS i FROM b WHERE len(w) > 0
), iw AS (
  SELECT DISTINCT item_id, m, array_to_string(list_slice(w, i, i + m - 1), ' ') AS k FROM bi
), di AS (
  SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM d, (SELECT DISTINCT m FROM iw) s WHERE len(w) >= m
), dw AS (
  SELECT doc_id, i, m, array_to_string(list_slice(w, i, i + m - 1), ' ') AS k FROM di
), found AS (
  SELECT DISTINCT dw.doc_id, dw.i, iw.m, iw.item_id FROM dw JOIN iw ON dw.k = iw.k AND dw.m = iw.m
), places AS (
  SELECT doc_id, unnest(range(i, i + m)) AS p FROM (SELECT DISTINCT doc_id, i, m FROM found) f
), hits AS (
  SELECT doc_id, count(DISTINCT p) AS n FROM places GROUP BY doc_id
), ids AS (
  SELECT doc_id, count(*) AS n, string_agg(s, ',' ORDER BY s) AS list
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM found) f GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(hits.n, 0) AS BIGINT) AS n_hit,
  CAST(coalesce(ids.n, 0) AS BIGINT) AS n_items, sha256(coalesce(ids.list, '')) AS items_sha256,
  coalesce(hits.n, 0) > 0 AND 20 * coalesce(hits.n, 0) >= len(d.w) AS contaminated
FROM d LEFT JOIN hits ON hits.doc_id = d.doc_id LEFT JOIN ids ON ids.doc_id = d.doc_id
"""
