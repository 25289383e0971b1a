"""Language-model scores from a probabilistic suffix tree over the bytes of normalised text.

A text's tokens are written as bytes: each lower-cased word and a blank behind it, then one
line feed as the end. The tree gives a token the probability of its bytes, each given the
longest context that is retained, of at most DEPTH bytes, across tokens.

Score: a token's chance is a mixture, the same for every token. WORDS of it is its relative
frequency in the training texts, after DISCOUNT is taken off its count; the rest, and what
the discounts leave, is the tree's probability of its bytes. A word that training never saw
is thus spelled through the tree, from longest retained suffix to longest retained suffix.
The chances of all byte strings add up to 1.

Tree: counts of all (DEPTH + 1)-grams of all training texts. A context is retained if its
next-byte distribution differs enough from that of its suffix one byte shorter: its count
times the Kullback-Leibler divergence must reach BITS, whatever the size of the corpus.
Suffixes of retained contexts are retained too. All retained contexts are kept, as tables
that grow with the corpus; none is collected or broadcast. Distributions are smoothed
towards the suffix's with the weight of the number of different next bytes; the root adds
one to every byte.

Scoring: the texts are packed in chunks of about CHUNK_BYTES. The chances of the FREQUENT_GRAMS
most frequent grams are broadcast. A chunk asks once for each other gram in it, meets the
tree's chances in a join, and looks its bytes up in what comes back.

Base score: words, as 64-bit hashes, are counted over all training texts. The counts of the
FREQUENT most frequent words are broadcast; other words of a document meet their counts in
a join.

Edge cases: a null text is empty and has the end as its only token; without training texts
c = N = V = 0 and all bytes are equally likely; rows with a null id
are scored, not learnt from; repeated rows count as often as they are there.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..plans.lineage import cut
from .common import SPACED, WordHasher, held_out, learnable, lengths, slices

DEPTH = 5
#: Bits that a context must gain: what it takes to name five bytes.
BITS = 40.0
#: Bytes of text that ask for their grams together.
CHUNK_BYTES = 16 << 20
#: Weight of word frequencies, and what is taken off each count.
WORDS, DISCOUNT = 0.5, 0.5
#: Words whose counts are broadcast (16 bytes each), and grams whose chances are (12 bytes each).
FREQUENT, FREQUENT_GRAMS = 300_000, 1_000_000
_END = 10
_PAD = bytes([_END]) * DEPTH
_CHUNK = 1 << 20
#: Distinct grams that a task holds before it emits them.
MOST_HELD = 2_000_000


def normal(text: bytes | None) -> bytes:
    """The bytes of a text's tokens."""
    w = text.translate(SPACED).split() if text else []
    return b" ".join(w) + b" \n" if w else b"\n"


def _column(batch, name: str) -> list:
    c = batch.column(batch.schema.get_field_index(name))
    if pa.types.is_string(c.type):
        c = c.cast(pa.binary())
    elif pa.types.is_large_string(c.type):
        c = c.cast(pa.large_binary())
    return c.to_pylist()


# -- the tree ----------------------------------------------------------------------------


def merged(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Codes, sorted and once each, with the sums of their counts."""
    codes, counts = np.concatenate([c for c, _ in parts]), np.concatenate([n for _, n in parts])
    order = np.argsort(codes, kind="stable")
    codes, counts = codes[order], counts[order]
    start = np.flatnonzero(np.diff(codes, prepend=codes[:1] - 1))
    return codes[start], np.add.reduceat(counts, start)


def _streams(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts, each behind its padding, and which of them are no padding."""
    pieces = [normal(t) for t in texts]
    stream = np.frombuffer(b"".join([_PAD + p for p in pieces]), np.uint8)
    own = np.ones(len(stream), bool)
    starts = np.cumsum([0, *(len(p) + DEPTH for p in pieces)])[:-1]
    for k in range(DEPTH):
        own[starts + k] = False
    return stream, own


def _codes(stream: np.ndarray, a: int, b: int) -> np.ndarray:
    """Codes of the (DEPTH + 1)-grams that end on the bytes from a to b."""
    codes = np.zeros(b - a, np.int64)
    for k in range(DEPTH, -1, -1):
        codes <<= 8
        codes |= stream[a - k : b - k]
    return codes


def gram_counts(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """Codes of all (DEPTH + 1)-grams that end on a byte of a text, and how often each is there."""
    stream, own = _streams(texts)
    if not len(stream):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    found = []
    for a in range(DEPTH, len(stream), _CHUNK):
        b = min(len(stream), a + _CHUNK)
        found.append(np.unique(_codes(stream, a, b)[own[a:b]], return_counts=True))
    return found[0] if len(found) == 1 else merged(found)


def _grams(rows: DataFrame) -> DataFrame:
    """(code, n): all grams of ``rows`` (text, learnt), and how often each is in learnt texts."""
    schema = T.StructType([T.StructField("code", T.LongType()), T.StructField("n", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []

        def out():
            codes, counts = merged(held)
            held.clear()
            for at in range(0, len(codes), 1 << 17):
                yield pa.RecordBatch.from_arrays([pa.array(codes[at : at + (1 << 17)]), pa.array(counts[at : at + (1 << 17)])], names=["code", "n"])

        for batch in batches:
            for a, b in slices(lengths(batch.column(0)), 4096, _CHUNK):
                texts, learnt = _column(part := batch.slice(a, b - a), "text"), part.column(1).to_pylist()
                held.append(gram_counts([t for t, x in zip(texts, learnt) if x]))
                others = gram_counts([t for t, x in zip(texts, learnt) if not x])[0]
                held.append((others, np.zeros(len(others), np.int64)))
                if sum(len(c) for c, _ in held) > MOST_HELD:
                    held[:] = [merged(held)]
                    if len(held[0][0]) > MOST_HELD // 2:
                        yield from out()
        if held:
            yield from out()

    return rows.select("text", "learnt").mapInArrow(run, schema).groupBy("code").agg(F.sum("n").alias("n"))


def levels(grams: DataFrame) -> list[DataFrame]:
    """Counts (code, n) of the k-grams for k = 1 ... DEPTH + 1."""
    out = [grams]
    for k in range(DEPTH, 0, -1):
        out.append(cut(out[-1].groupBy(F.col("code").bitwiseAND(F.lit((1 << 8 * k) - 1)).alias("code")).agg(F.sum("n").alias("n"))))
    return out[::-1]


def divergences(tables: list[DataFrame], k: int) -> DataFrame:
    """(context, whole, kinds, gain) of the contexts of depth k: count, different next bytes, count times divergence from the suffix."""
    context = F.shiftright("code", 8)
    below = tables[k - 1].where("n > 0").withColumn("suffix", context).select(F.col("code").alias("tail"), "suffix", F.col("n").alias("m"))
    whole = below.groupBy("suffix").agg(F.sum("m").alias("all_m"))
    low = below.join(whole, "suffix").select("tail", F.log2(F.col("m") / F.col("all_m")).alias("p"))
    here = tables[k].where("n > 0").select(context.alias("context"), "n", F.col("code").bitwiseAND(F.lit((1 << 8 * k) - 1)).alias("tail"))
    sums = here.join(low, "tail").groupBy("context").agg(
        F.sum("n").alias("whole"), F.count("*").alias("kinds"), F.sum(F.col("n") * F.log2(F.col("n").cast("double"))).alias("own"), F.sum(F.col("n") * F.col("p")).alias("cross")
    )
    gain = F.col("own") - F.col("whole") * F.log2(F.col("whole").cast("double")) - F.col("cross")
    return sums.select("context", "whole", "kinds", gain.alias("gain"))


def retained(tables: list[DataFrame], bits: float = BITS) -> list[DataFrame]:
    """(context, whole, kinds) of all contexts of depths 1 ... DEPTH that gain ``bits`` or are suffixes of one that does."""
    out: list[DataFrame] = []
    for k in range(DEPTH, 0, -1):
        rows, keep = divergences(tables, k), F.col("gain") >= bits
        if out:
            suffixes = out[-1].select(F.col("context").bitwiseAND(F.lit((1 << 8 * k) - 1)).alias("context")).distinct()
            rows, keep = rows.join(suffixes.withColumn("longer", F.lit(True)), "context", "left"), keep | F.col("longer").isNotNull()
        out.append(cut(rows.where(keep).select("context", "whole", "kinds")))
    return out[::-1]


def chances(tables: list[DataFrame], contexts: list[DataFrame]) -> DataFrame:
    """(code, log): log10 of the chance of the last byte of each (DEPTH + 1)-gram of ``tables`` behind its longest retained context."""
    total = tables[0].agg(F.sum("n")).first()[0] or 0
    p = tables[0].select("code", ((F.col("n") + 1) / F.lit(total + 256.0)).alias("p"))
    for k in range(1, DEPTH + 1):
        rows = tables[k].select("code", "n", F.shiftright("code", 8).alias("context"), F.col("code").bitwiseAND(F.lit((1 << 8 * k) - 1)).alias("tail"))
        rows = rows.join(p.select(F.col("code").alias("tail"), F.col("p").alias("below")), "tail").join(contexts[k - 1], "context", "left")
        smoothed = (F.col("n") + F.col("kinds") * F.col("below")) / (F.col("whole") + F.col("kinds"))
        p = rows.select("code", F.coalesce(smoothed, "below").alias("p"))
    return p.select("code", F.log10("p").cast("float").alias("log"))


def build(contexts: list[set[int]], counts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> dict:
    """Arrays of the tree: next state by older byte, and log10 chances of the next byte, over the bytes seen.

    ``contexts[k]`` holds the retained contexts of depth k (suffix-closed, k from 1);
    ``counts[k]`` the (context, byte, count) arrays of those of depth k.
    """
    root = np.zeros(256, np.int64)
    root[counts[0][1]] = counts[0][2]
    seen = np.flatnonzero(root)
    width = len(seen) + 1  # the last column stands for all bytes not seen
    column = np.full(256, width - 1, np.int64)
    column[seen] = np.arange(len(seen))
    states = 1 + sum(map(len, contexts[1:]))
    chance = np.zeros((states, width))
    chance[0] = np.append(root[seen] + 1, 1) / (root.sum() + 256)
    child = np.full((states + 1, width), states, np.int32)
    ids: dict[int, int] = {0: 0}
    at = 1
    for k in range(1, DEPTH + 1):
        order = np.array(sorted(contexts[k]), np.int64)
        if not len(order):
            break
        new = np.arange(at, at + len(order))
        parents = np.array([ids[int(c) & ((1 << 8 * (k - 1)) - 1)] for c in order])
        child[parents, column[order >> 8 * (k - 1)]] = new
        table = np.zeros((len(order), width))
        c, b, n = counts[k]
        table[np.searchsorted(order, c), column[b]] = n
        weight = np.maximum((table > 0).sum(axis=1, keepdims=True), 1)
        chance[new] = (table + weight * chance[parents]) / (table.sum(axis=1, keepdims=True) + weight)
        ids = dict(zip(order.tolist(), new.tolist()))
        at += len(order)
    return {"column": column.astype(np.int32), "child": child.ravel(), "width": width, "dead": states, "log": np.log10(chance).astype(np.float32).ravel()}


def learn(docs: DataFrame, bits: float = BITS) -> dict:
    """The whole tree from all texts of ``docs`` (text) as arrays, to look at: scoring never collects it."""
    tables = levels(cut(_grams(docs.select("text", F.lit(True).alias("learnt")))))
    kept = retained(tables, bits)
    contexts: list[set[int]] = [{0}] + [set(c.toArrow().column("context").to_pylist()) for c in kept]
    counts = []
    for k in range(DEPTH + 1):
        rows = tables[k].select(F.shiftright("code", 8).alias("context"), F.col("code").bitwiseAND(F.lit(255)).alias("b"), "n")
        found = (rows.join(kept[k - 1], "context", "left_semi") if k else rows).toArrow()
        counts.append(tuple(found.column(c).to_numpy() for c in ("context", "b", "n")))
    return build(contexts, counts)


# -- chunks of texts -----------------------------------------------------------------------


def packed(rows: DataFrame) -> DataFrame:
    """(chunk, data): ``rows`` (with text) as compressed Arrow streams, in chunks of about CHUNK_BYTES."""
    schema = T.StructType([T.StructField("chunk", T.LongType()), T.StructField("data", T.BinaryType())])
    at = rows.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        options = pa.ipc.IpcWriteOptions(compression="zstd")
        first, done = TaskContext.get().partitionId() << 32, 0
        for batch in batches:
            sizes = lengths(batch.column(at))
            for a, b in slices(sizes, 4096, _CHUNK):
                part, sink = batch.slice(a, b - a), pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, part.schema, options=options) as writer:
                    writer.write_batch(part)
                yield pa.RecordBatch.from_arrays([pa.array([first + done // CHUNK_BYTES]), pa.array([sink.getvalue().to_pybytes()])], names=["chunk", "data"])
                done += int(sizes[a:b].sum()) + b - a

    return rows.mapInArrow(run, schema)


def _unpacked(data: bytes) -> Iterator[pa.RecordBatch]:
    with pa.ipc.open_stream(data) as reader:
        yield from reader


def asked_grams(chunks: DataFrame, frequent) -> DataFrame:
    """(chunk, code): the different grams of each chunk that are not among the ``frequent`` (a broadcast of sorted codes
    and logs); a gram may be there more than once if the chunk holds many."""
    schema = T.StructType([T.StructField("chunk", T.LongType()), T.StructField("code", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, chunk = [], None
        known = frequent.value[0]

        def out():
            codes = np.unique(np.concatenate(held))
            held.clear()
            if len(known):
                codes = codes[known[np.minimum(np.searchsorted(known, codes), len(known) - 1)] != codes]
            for at in range(0, len(codes), 1 << 17):
                part = codes[at : at + (1 << 17)]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), chunk)), pa.array(part)], names=["chunk", "code"])

        for batch in batches:
            for c, data in zip(batch.column(0).to_pylist(), batch.column(1)):
                if held and (c != chunk or sum(map(len, held)) > MOST_HELD):
                    yield from out()
                chunk = c
                for part in _unpacked(data.as_buffer()):
                    held.append(gram_counts(_column(part, "text"))[0])
        if held:
            yield from out()

    return chunks.mapInArrow(run, schema)


def token_logs(texts: list[bytes | None], codes: np.ndarray, logs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The tree's log10 probability of each token of the texts in turn, and which tokens are ends; ``codes`` are sorted."""
    stream, own = _streams(texts)
    out = np.zeros(len(stream))
    for a in range(DEPTH, len(stream), _CHUNK):
        b = min(len(stream), a + _CHUNK)
        out[a:b][own[a:b]] = logs[np.searchsorted(codes, _codes(stream, a, b)[own[a:b]])]
    last = np.flatnonzero(((stream == _END) & own) | (stream == 32))
    return np.diff(np.cumsum(out)[last], prepend=0.0), stream[last] == _END


# -- words ---------------------------------------------------------------------------------


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, n): hashes of all words of ``docs`` (text) and how often each is there."""
    schema = T.StructType([T.StructField("word", T.LongType()), T.StructField("n", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, held = WordHasher(SPACED), []

        def out():
            words, counts = merged(held)
            held.clear()
            for at in range(0, len(words), 1 << 17):
                yield pa.RecordBatch.from_arrays([pa.array(words[at : at + (1 << 17)]), pa.array(counts[at : at + (1 << 17)])], names=["word", "n"])

        for batch in batches:
            for a, b in slices(lengths(batch.column(0)), 4096):
                hashes, _ = hasher(_column(batch.slice(a, b - a), "text"))
                held.append(np.unique(hashes.view(np.int64), return_counts=True))
                if sum(len(c) for c, _ in held) > MOST_HELD:
                    held[:] = [merged(held)]
                    if len(held[0][0]) > MOST_HELD // 2:
                        yield from out()
        if held:
            yield from out()

    return docs.select("text").mapInArrow(run, schema).groupBy("word").agg(F.sum("n").alias("n"))


def most_frequent(table: DataFrame, most: int) -> DataFrame:
    """Words of ``table`` (word, n) from a count on, as low as leaves at most ``most`` of them: found without a sort."""
    step = F.floor(F.log2(F.col("n").cast("double")) * 8)
    least, room = None, most
    for r in sorted(table.groupBy(step.alias("step")).agg(F.count("*").alias("c"), F.min("n").alias("low")).collect(), key=lambda r: -r.step):
        room -= r.c
        if room < 0:
            break
        least = r.low
    return table.where(F.lit(False) if least is None else F.col("n") >= least)


def score_documents(
    docs: DataFrame, id_col: str = "doc_id", text: str = "text", parts: int = 7, part: int = 2,
    frequent: int = FREQUENT, frequent_grams: int = FREQUENT_GRAMS, bits: float = BITS,
) -> DataFrame:
    """(id_col, held_out, n_tokens, n_known, train_tokens, base_score, score), a row for each of ``docs``."""
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    rows = rows.withColumn("learnt", learnable(F.col("id"), parts, part))
    learnt = rows.where("learnt").select("text")
    ends = learnt.count()
    grams = cut(_grams(rows))
    tables = levels(grams)
    chance_of = cut(chances(tables, retained(tables, bits)))
    table = cut(word_counts(learnt))
    words, distinct = table.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    total, kinds = words + ends, distinct + (ends > 0)
    word_share = WORDS / max(total, 1)
    tree_share = 1 - WORDS + WORDS * DISCOUNT * kinds / max(total, 1) if total else 1.0
    tree_log = float(np.log10(tree_share))
    context = docs.sparkSession.sparkContext
    top = most_frequent(table, frequent).toArrow().sort_by("word")
    held = context.broadcast((top.column("word").to_numpy(), top.column("n").to_numpy()))
    top = chance_of.join(most_frequent(grams.where("n > 0"), frequent_grams).select("code"), "code", "left_semi").toArrow().sort_by("code")
    spelled = context.broadcast((top.column("code").to_numpy(), top.column("log").to_numpy()))

    long, double = T.LongType(), T.DoubleType()
    fields = [("n_tokens", long), ("n_top", long), ("log_top", double), ("score_top", double), ("rare", T.ArrayType(long)), ("rare_tree", T.ArrayType(double))]
    schema = T.StructType([rows.schema["id"], T.StructField("row", long)] + [T.StructField(n, t) for n, t in fields])
    arrow = to_arrow_schema(schema)

    def sums(values, bounds):
        return np.diff(np.concatenate([[0.0], np.cumsum(values)])[bounds])

    def log_chance(counts, tree):
        """A token never seen has the tree's chance only; logs keep those of long words from vanishing."""
        seen = counts > 0
        return np.where(seen, np.log10(np.where(seen, word_share * (counts - DISCOUNT), 1.0) + tree_share * 10.0**tree), tree_log + tree)

    def scored(chunk: pa.Table, answers: pa.Table) -> pa.Table:
        known, counts = held.value
        codes = np.concatenate([spelled.value[0], answers.column("code").to_numpy()])
        logs = np.concatenate([spelled.value[1], answers.column("log").to_numpy()])
        order = np.argsort(codes, kind="stable")
        codes, logs = codes[order], logs[order]
        hasher, out = WordHasher(SPACED), []
        for data in chunk.column("data"):
            for batch in _unpacked(data.as_buffer()):
                texts = _column(batch, "text")
                hashes, bounds = hasher(texts)
                hashes = hashes.view(np.int64)
                by_tree, end = token_logs(texts, codes, logs)
                word_tree, end_tree = by_tree[~end], by_tree[end]
                common, c = np.zeros(len(hashes), bool), np.zeros(len(hashes))
                if len(known):
                    at = np.minimum(np.searchsorted(known, hashes), len(known) - 1)
                    common = known[at] == hashes
                    c = np.where(common, counts[at], 0)
                score = sums(np.where(common, log_chance(c, word_tree), 0.0), bounds) + log_chance(np.full(len(end_tree), float(ends)), end_tree)
                seen = np.concatenate([[0], np.cumsum(common)])
                places = pa.array((bounds - seen[bounds]).astype(np.int32))
                rare = pa.ListArray.from_arrays(places, pa.array(hashes[~common]))
                rare_tree = pa.ListArray.from_arrays(places, pa.array(word_tree[~common]))
                made = [np.diff(bounds) + 1, np.diff(seen[bounds]), sums(np.where(common, np.log10(c + 1.0), 0.0), bounds), score, rare, rare_tree]
                made = [batch.column(batch.schema.get_field_index("id")), batch.column(batch.schema.get_field_index("row")), *made]
                out.append(pa.Table.from_arrays([pa.array(m) if isinstance(m, np.ndarray) else m for m in made], names=arrow.names).cast(arrow))
        return pa.concat_tables(out)

    chunks = cut(packed(rows.select("id", "text").withColumn("row", F.monotonically_increasing_id())))
    answers = asked_grams(chunks, spelled).join(chance_of, "code").select("chunk", "code", "log")
    first = cut(chunks.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(scored, schema))
    asked = first.select("row", F.inline(F.arrays_zip(F.col("rare").alias("word"), F.col("rare_tree").alias("tree"))))
    spelt = F.lit(tree_log) + F.col("tree")
    chance = F.log10(F.lit(word_share) * (F.col("n") - DISCOUNT) + F.lit(tree_share) * F.pow(F.lit(10.0), F.col("tree")))
    found = asked.join(table, "word", "left").groupBy("row").agg(
        F.count("n").alias("n_rare"), F.sum(F.when(F.col("n").isNotNull(), F.log10(F.col("n") + 1.0)).otherwise(0.0)).alias("log_rare"),
        F.sum(F.when(F.col("n").isNotNull(), chance).otherwise(spelt)).alias("score_rare"),
    )
    both = first.select("id", "row", "n_tokens", "n_top", "log_top", "score_top").join(found, "row", "left")
    n_rare = F.coalesce("n_rare", F.lit(0))
    logs = F.col("log_top") + F.coalesce("log_rare", F.lit(0.0)) + float(np.log10(ends + 1.0))
    score = F.col("score_top") + F.coalesce("score_rare", F.lit(0.0))
    return both.select(
        F.col("id").alias(id_col), held_out(F.col("id"), parts, part).alias("held_out"), "n_tokens",
        (F.col("n_top") + n_rare + int(ends > 0)).alias("n_known"), F.lit(int(total)).cast("bigint").alias("train_tokens"),
        (logs - F.col("n_tokens") * float(np.log10(total + kinds + 1.0))).alias("base_score"), score.alias("score"),
    )


def op6_language_model(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return score_documents(docs)
