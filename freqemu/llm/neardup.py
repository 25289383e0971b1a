"""Near-duplicates by min-max hashing, banding and exact confirmation.

Each of K linear permutations of 32 bits is evaluated once over a document's shingles and
gives two signature values, the minimum and the maximum, so 2K values cost K evaluations.
The values lie in bands of R different permutations; documents that agree in a band are
candidates. The chance that a pair of similarity 0.8 shares none of the 40 bands of 6 is
about 5e-6; every candidate is confirmed on the full shingle sets, so no false link stays.

No pairs inside a group are listed: documents with equal sets are one class; in a bucket
every class is first paired with the bucket's smallest class only; confirmed links are
made into components; only members of buckets that still hold several components go on.
Among those, links across components are searched with an exact prefix filter: shingles
are ordered from rare to frequent, and two similar sets must share one of their first few
shingles, how few depends on both sizes. In a large group of near copies the first
shingles of a copy are its own changes, so copies that only resemble each other's source
are never paired. Shingles are paired inside ranges of set sizes that can be similar, and
members of a shingle's main component only with the others. Components come from rounds of
large-star and small-star steps over a links table, checkpointed in the shared folder.

Hot keys: a class with many pairs meets them in shares of SHARE, each with the class's set
once; keys of the links table with many rows (at most HEAVY keys can have so many) are looked up
in a broadcast, all others by a shuffle of keys whose groups are that small.

Edge cases: a null or word-less text has an empty set and links with nothing; a document
shorter than the shingle is one shingle; rows that repeat a doc_id are one document that
is linked if any of its texts is; rows with a null id link with nothing (``keep_one`` lets
copies among them go).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window as W, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..plans.lineage import cut
from .common import SPACED, WordHasher, annotate, free_names, mix, shingles

BANDS, ROWS = 40, 6
#: Candidate documents up to this number are broadcast to the second reading of texts (16 bytes each); beyond it a shuffle joins them.
BROADCAST_IDS = 400_000
#: Pairs that meet one copy of the set they share.
SHARE = 256
#: Keys with more than LIGHT rows and more than one in HEAVY of all rows are looked up by broadcast: at most HEAVY keys.
LIGHT, HEAVY = 512, 50_000
#: Rows up to which a whole table is looked up by broadcast (24 bytes each).
FEW_ROWS = 200_000


def permutations(count: int) -> tuple[np.ndarray, np.ndarray]:
    """Odd factors and offsets of 32 bits, the same on every machine."""
    seeds = mix(np.arange(1, 2 * count + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    values = (seeds >> np.uint64(32)).astype(np.uint32)
    return values[:count] | np.uint32(1), values[count:]


def signature(sets: np.ndarray, factors: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Minimum and maximum of the sets' hashes under each permutation."""
    x = (sets >> np.uint64(32)).astype(np.uint32)
    low, high = [], []
    for at in range(0, len(x), 8192):
        part = factors[:, None] * x[None, at : at + 8192] + offsets[:, None]
        low.append(part.min(axis=1))
        high.append(part.max(axis=1))
    return np.concatenate([np.min(low, axis=0), np.max(high, axis=0)])


def band_keys(values: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One 64-bit key for each band; equal keys of different bands do not meet."""
    out = np.arange(1, bands + 1, dtype=np.uint64)
    for column in values[: bands * rows].reshape(bands, rows).T:
        out = mix(out * np.uint64(0x9E3779B97F4A7C15) + column.astype(np.uint64))
    return out.view(np.int64)


def _signed(docs: DataFrame, id_col: str, text: str, width: int, bands: int, rows: int) -> DataFrame:
    def start():
        hasher = WordHasher(SPACED)
        factors, offsets = permutations(bands * rows // 2)

        def work(texts):
            n, keys, signs = [], [], []
            hashes, bounds = hasher(texts)
            for a, b in zip(bounds, bounds[1:]):
                s = shingles(hashes[a:b], width)
                n.append(len(s))
                keys.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                signs.append(band_keys(signature(s, factors, offsets), bands, rows) if len(s) else None)
            return n, keys, signs

        return work

    fields = [("n", T.IntegerType()), ("key", T.BinaryType()), ("bands", T.ArrayType(T.LongType()))]
    return annotate(docs.select(F.col(id_col).alias("id"), F.col(text).alias("text")), ["text"], fields, start, keep=["id"])


def _sets(docs: DataFrame, id_col: str, text: str, width: int, wanted: DataFrame) -> DataFrame:
    """(id, key, set) of the ``wanted`` classes, from a second reading of the texts."""
    few = wanted.count() <= BROADCAST_IDS
    side = F.broadcast(wanted.select("id").distinct()) if few else wanted.select("id").distinct()
    rows = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text")).where("text is not null").join(side, "id", "left_semi")

    def start():
        hasher = WordHasher(SPACED)

        def work(texts):
            hashes, bounds = hasher(texts)
            sets = [shingles(hashes[a:b], width) for a, b in zip(bounds, bounds[1:])]
            return [xxhash.xxh3_128_digest(s.tobytes()) for s in sets], [s.tobytes() for s in sets]

        return work

    found = annotate(rows, ["text"], [("key", T.BinaryType()), ("set", T.BinaryType())], start, keep=["id"])
    return found.join(wanted, ["id", "key"], "left_semi").dropDuplicates(["id", "key"])


def _sets_of(docs, id_col, text, width, classes, ids) -> DataFrame:
    wanted = cut(classes.select("id", "key").join(ids, "id", "left_semi"))
    return cut(_sets(docs, id_col, text, width, wanted))


def looked_up(rows: DataFrame, table: DataFrame, key: str, size: str, total: int) -> DataFrame:
    """Inner join of ``rows`` with ``table`` on ``key``; ``size`` bounds from below how many rows have the key.

    ``table`` has one row a key; sizes of all keys sum to ``total`` at most.
    """
    if total <= FEW_ROWS:
        return rows.join(F.broadcast(table), key)
    many = max(LIGHT, total // HEAVY)
    heavy, light = table.where(F.col(size) > many), table.where(F.col(size) <= many)
    return rows.join(F.broadcast(heavy), key).unionByName(rows.join(F.broadcast(heavy.select(key)), key, "left_anti").join(light, key))


def _across(sets: DataFrame, members: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of ``members`` (id, component) in different components that may be similar enough: no link is missing.

    Sets with at least ``percent`` in common share o = percent * (n + m) / (100 + percent)
    shingles or more; so the first shared one, in any common order, stands among the first
    n - o + 1 of the one and the first m - o + 1 of the other. Shingles of a single set
    come first in the order and are shared by none, so they are only counted.
    """

    def start():
        return lambda sets: [[np.frombuffer(x, np.int64) for x in sets]]

    listed = annotate(sets.join(members, "id"), ["set"], [("shingles", T.ArrayType(T.LongType()))], start, keep=["id", "component"])
    tokens = cut(listed.select("id", "component", F.size("shingles").alias("n"), F.explode("shingles").alias("token")))
    common = tokens.groupBy("token").agg(F.count("*").alias("f")).where("f > 1")
    shared = tokens.join(common, "token")  # slim rows, a row of counts a token: a hot one is split by AQE's skew join
    by = W.partitionBy("id", "component", "n").orderBy("f", "token")
    placed = shared.withColumn("k", F.row_number().over(by)).withColumn("all", F.count("*").over(W.partitionBy("id", "component", "n")))
    first = placed.withColumn("at", F.col("n") - F.col("all") + F.col("k")).where(f"100 * (n - at + 1) >= {percent} * n").select("id", "component", "n", "token", "at")
    # sets in sizes of one range, or of two that follow each other, may be similar
    step = float(np.log(100 / percent)) if percent < 100 else 1e-9
    first = cut(first.withColumn("span", F.floor(F.log("n") / step + 1e-9).cast("long")))
    groups = first.groupBy("token", "component").agg(F.count("*").alias("c")).groupBy("token").agg(F.max_by("component", F.struct("c", "component")).alias("main"), F.sum("c").alias("rows"), F.count("*").alias("kinds"))
    mixed = cut(first.join(groups.where("kinds > 1").drop("kinds"), "token"))
    # the others of a token meet all its rows; a token's rows are dealt over shares
    shares = (F.col("rows") / LIGHT).cast("int") + 1
    q = mixed.withColumn("share", F.pmod(F.xxhash64("id"), shares).cast("int")).alias("q")
    p = mixed.where("component <> main").withColumn("share", F.explode(F.sequence(F.lit(0), shares - 1)))
    p = p.withColumn("span", F.explode(F.array(F.col("span") - 1, F.col("span"), F.col("span") + 1))).alias("p")
    least = f"{percent} * (p.n + q.n)"
    return p.join(q, (F.col("p.token") == F.col("q.token")) & (F.col("p.span") == F.col("q.span")) & (F.col("p.share") == F.col("q.share"))).where(
        f"p.component <> q.component and (p.id < q.id or q.component = q.main) and {100 + percent} * (p.n - p.at + 1) >= {least} and {100 + percent} * (q.n - q.at + 1) >= {least}"
        f" and 100 * least(p.n, q.n) >= {percent} * greatest(p.n, q.n)"
    ).select(F.least("p.id", "q.id").alias("a"), F.greatest("p.id", "q.id").alias("b")).distinct()


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Those of ``pairs`` (a, b) whose full sets are similar enough.

    Of the two ends of a pair, the one with more pairs is its hub. A hub's pairs are dealt
    over shares of about SHARE; each share is one run of rows, the hub's set first, so it
    is sent once for a share and not once for a pair.
    """
    degree = pairs.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count("*").alias("n"))
    many = cut(degree.where(F.col("n") > SHARE))  # ends with fewer pairs need no count
    few = many.count()
    sized = pairs
    for end in ("a", "b"):
        side = many.select(F.col("id").alias(end), F.col("n").alias(f"n{end}"))
        if few:
            sized = sized.join(F.broadcast(side) if few <= FEW_ROWS else side, end, "left").withColumn(f"n{end}", F.coalesce(f"n{end}", F.lit(1)))
        else:
            sized = sized.withColumn(f"n{end}", F.lit(1))
    swap = F.col("nb") > F.col("na")
    dealt = cut(sized.select(
        F.when(swap, F.col("b")).otherwise(F.col("a")).alias("hub"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("id"),
        (F.greatest("na", "nb") / SHARE).cast("int").alias("shares"), swap.alias("swap"),
    ).withColumn("share", F.pmod(F.xxhash64("id"), F.col("shares") + 1).cast("int")))
    columns = ["hub", "share", "id", "swap", "set"]
    heads = dealt.select("hub", "share").distinct().join(sets.select(F.col("id").alias("hub"), "set"), "hub").withColumn("id", F.lit(None).cast(sets.schema["id"].dataType)).withColumn("swap", F.lit(False))
    rows = heads.select(columns).unionByName(dealt.join(sets.select("id", "set"), "id").select(columns))
    runs = rows.repartition("hub", "share").sortWithinPartitions("hub", "share", F.col("id").asc_nulls_first())
    id_type = sets.schema["id"].dataType
    schema = T.StructType([T.StructField("a", id_type), T.StructField("b", id_type)])
    arrow = to_arrow_schema(schema)

    def run(batches):
        head, hub = None, None
        for batch in batches:
            hubs, _, ids, swaps, found = (batch.column(k) for k in range(5))
            hubs, ids, swaps = hubs.to_pylist(), ids.to_pylist(), swaps.to_pylist()
            good = []
            for k, other in enumerate(ids):
                q = np.frombuffer(found[k].as_buffer(), np.uint64)
                if other is None:
                    head, hub = q.copy(), hubs[k]
                    continue
                if hub != hubs[k]:
                    raise ValueError("a pair stands without its hub")
                if 100 * min(len(head), len(q)) < percent * max(len(head), len(q)):
                    continue
                met = len(np.intersect1d(head, q, assume_unique=True))
                if 100 * met >= percent * (len(head) + len(q) - met):
                    good.append((other, hub) if swaps[k] else (hub, other))
            yield pa.RecordBatch.from_arrays([pa.array([g[e] for g in good], arrow.field(e).type) for e in (0, 1)], names=["a", "b"])

    return cut(runs.mapInArrow(run, schema).distinct())


def components(links: DataFrame) -> DataFrame:
    """(id, component): the smallest id that ``links`` (a, b) lead to, for every id in a link."""
    edges = cut(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())

    def state(e):
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    before = state(edges)
    while before[0]:
        # large star: every larger neighbour gets the smallest id around
        both = edges.select(F.explode(F.array(F.struct("u", "v"), F.struct(F.col("v").alias("u"), F.col("u").alias("v")))).alias("e")).select("e.*")
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("near"))
        total = before[0] * 2
        large = looked_up(edges.select(F.col("u").alias("w"), F.col("v").alias("u")), least, "u", "near", total).where("w <> m").select(F.col("w").alias("u"), F.col("m").alias("v")).union(
            least.where("m <> u").select("u", F.col("m").alias("v"))
        ).distinct()
        # small star: smaller neighbours and the id itself get the smallest of them
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("near"))
        small = looked_up(large, low, "u", "near", total).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).distinct()
        edges = cut(small)
        after = state(edges)
        if after == before:
            break
        before = after
    return edges.groupBy(F.col("u").alias("id")).agg(F.min("v").alias("component")).union(
        edges.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    ).groupBy("id").agg(F.min("component").alias("component"))


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS,
) -> DataFrame:
    """(id, n_shingles, component) for every row of ``docs``."""
    signed = cut(_signed(docs, id_col, text, width, bands, rows))
    known = signed.where("key is not null and id is not null")
    classes = cut(known.groupBy("key").agg(F.min("id").alias("id"), F.min("n").alias("n"), F.min_by("bands", "id").alias("bands")))
    spread = classes.select("id", "n", F.explode("bands").alias("band"))
    heads = spread.groupBy("band").agg(F.min("id").alias("head"), F.max("id").alias("last"), F.min_by("n", "id").alias("head_n")).where("head < last")
    members = cut(spread.join(heads.select("band", "head", "head_n"), "band"))
    sized = F.least("n", "head_n") * 100 >= F.greatest("n", "head_n") * percent
    stars = cut(members.where((F.col("id") != F.col("head")) & sized).select(F.col("head").alias("a"), F.col("id").alias("b")).distinct())
    ends = stars.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    links = _confirmed(stars, _sets_of(docs, id_col, text, width, classes, ends), percent)
    label = cut(components(links))

    inside = members.select("id", "band").join(label, "id", "left").withColumn("component", F.coalesce("component", "id"))
    mixed = inside.groupBy("band").agg(F.min("component").alias("x"), F.max("component").alias("y")).where("x < y").select("band")
    rest = cut(inside.join(mixed, "band", "left_semi").select("id", "component").distinct())
    if not rest.isEmpty():
        sets = _sets_of(docs, id_col, text, width, classes, rest.select("id"))
        more = _confirmed(cut(_across(sets, rest, percent)), sets, percent)
        label = cut(components(links.union(more)))
    named = classes.select("key", F.col("id").alias("class")).join(label.withColumnRenamed("id", "class"), "class", "left")
    named = named.select("key", F.coalesce("component", "class").alias("component"))
    out = signed.select("id", "n", "key").join(named, "key", "left")
    # rows of one document with several texts share the smallest component of their texts
    repeated = known.groupBy("id").agg(F.count_distinct("key").alias("k")).where("k > 1").select("id")
    if not repeated.isEmpty():
        extra = out.join(repeated, "id", "left_semi").where("component is not null").select(F.col("id").alias("a"), F.col("component").alias("b"))
        again = cut(components(extra.union(extra.select("b", "b"))))
        out = out.join(again.select(F.col("id").alias("component"), F.col("component").alias("joined")), "component", "left")
        out = out.withColumn("component", F.coalesce("joined", "component"))
    return out.select("id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("component", "id").alias("component"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 5, percent: int = 80) -> DataFrame:
    """One row of ``docs`` for each group: that of the smallest id; of its repeated rows the one with the smallest text.

    Rows with a null id go if a row with an id has the same text; of equal texts among
    them one stays. Those without a text all stay. Near copies under null ids stay too.
    """
    found = near_duplicates(docs, id_col, text, width, percent)
    name = free_names(["gone"], docs.columns)[0]
    gone = cut(found.where("id <> component").select(F.col("id").alias(name)).distinct())
    side = F.broadcast(gone) if gone.count() <= BROADCAST_IDS else gone
    ident, body = F.col(f"`{id_col}`"), F.col(f"`{text}`")
    out = docs.join(side, ident == F.col(name), "left_anti")
    again = cut(out.where(ident.isNotNull()).groupBy(ident.alias(name)).count().where("count > 1").select(name))
    many = again.count()
    if many:
        again = F.broadcast(again) if many <= BROADCAST_IDS else again
        single = _least_row(out.join(again, ident == F.col(name), "left_semi"), ident, body)
        out = out.join(again, ident == F.col(name), "left_anti").unionByName(single)
    nameless = docs.where(ident.isNull())
    if not nameless.isEmpty():
        texts = docs.where(ident.isNotNull() & body.isNotNull()).select(body.alias(name))
        fresh = _least_row(nameless.where(body.isNotNull()).join(texts, body == F.col(name), "left_anti"), F.sha2(body.cast("binary"), 256), body)
        out = out.where(ident.isNotNull()).unionByName(nameless.where(body.isNull())).unionByName(fresh)
    return out


def _least_row(rows: DataFrame, group: Column, first: Column) -> DataFrame:
    """One row of each ``group``, by ``first`` and a hash of the row; combined before the shuffle."""
    every = [F.col(f"`{c}`") for c in rows.columns]
    best = F.min_by(F.struct(*every), F.struct(first.alias("a"), F.xxhash64(*every).alias("b")))
    return rows.groupBy(group.alias("_group")).agg(best.alias("_row")).select("_row.*")


def op2_near_duplicates(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = near_duplicates(docs, width=2, percent=80)
    return found.select(F.col("id").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"), F.col("id").eqNullSafe(F.col("component")).alias("kept"))


OP2_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), places AS (
  SELECT doc_id, w, unnest(range(1, greatest(len(w) - 1, 1) + 1)) AS i FROM d WHERE len(w) > 0
), s AS (
  SELECT DISTINCT doc_id, array_to_string(list_slice(w, i, i + 1), ' ') AS k FROM places
), n AS (
  SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id
), common AS (
  SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.k = y.k AND x.doc_id < y.doc_id GROUP BY x.doc_id, y.doc_id
), links AS (
  SELECT a, b FROM common JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 80 * (p.n + q.n - c)
), both_ways AS (
  SELECT a, b FROM links UNION SELECT b, a FROM links
), reach(id, r) AS (
  SELECT doc_id, doc_id FROM n
  UNION
  SELECT reach.id, both_ways.b FROM reach JOIN both_ways ON both_ways.a = reach.r
), c AS (
  SELECT id, min(r) AS r FROM reach GROUP BY id
)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, coalesce(c.r, d.doc_id) AS component_id, d.doc_id = coalesce(c.r, d.doc_id) AS kept
FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN c ON c.id = d.doc_id
"""
