"""Preference formatting: one prompt, two masked completions.

A pair's prompt is the longest common prefix of turns of its chosen and its rejected
conversation, rendered once; what follows in each is its completion. A completion is a
list of segments with a mask: 1 where a model learns (text of assistant turns and the end
mark behind it), 0 elsewhere. If one conversation is a prefix of the other, its last
assistant turn and what follows leave the prompt, so that the completion is not empty
where that is possible.

Pairs: conversations that open with the same turn stand in order of their ids; each is
chosen once, against the next one as rejected. The last of a group, and so every
conversation without a companion, has no rejected side: its prompt is everything before
its last assistant turn. Turns have the order of their turn number, then role, then text.

Edge cases: turns with a null conversation or turn number are left out; null roles and
texts are rendered as empty; repeated turns stay; an empty table gives no pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..plans.lineage import cut

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def rendered(turn: Column) -> Column:
    return F.concat(F.lit(OPEN), turn["role"], F.lit("\n"), turn["text"], F.lit(CLOSE + "\n"))


def prompt_of(turns: Column) -> Column:
    return F.array_join(F.transform(turns, rendered), "")


def segments(turns: Column) -> Column:
    """(text, mask) pieces of rendered turns: an assistant's words and end mark are learnt."""

    def pieces(t):
        learn = F.when(t["role"] == "assistant", 1).otherwise(0)
        return F.array(
            F.struct(F.concat(F.lit(OPEN), t["role"], F.lit("\n")).alias("text"), F.lit(0).alias("mask")),
            F.struct(F.concat(t["text"], F.lit(CLOSE)).alias("text"), learn.alias("mask")),
            F.struct(F.lit("\n").alias("text"), F.lit(0).alias("mask")),
        )

    return F.flatten(F.transform(turns, pieces))


def gathered(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(conv, turns): one row a conversation, its turns in order."""
    rows = turns.where(F.col(conv).isNotNull() & F.col(turn).isNotNull()).select(
        F.col(conv).alias("conv"), F.col(turn).alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")
    )
    listed = rows.groupBy("conv").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    return listed.select("conv", F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))


def paired(conversations: DataFrame) -> DataFrame:
    """(chosen_id, rejected_id, chosen, rejected) from (conv, turns).

    Keys are dealt by ranges of (group, id): a group of any size, with ids of any kind, is
    spread over as many ranges as it fills. The next id is found inside a range; behind its
    last row follows the first of the next range, one row a range.
    """
    keys = conversations.select("conv", F.xxhash64(F.element_at("turns", 1)).alias("a"), F.md5(F.concat_ws("\x01", F.element_at("turns", 1)["role"], F.element_at("turns", 1)["text"])).alias("b"))
    order = ["a", "b", "conv"]
    keys = cut(keys.repartitionByRange(*[F.col(c) for c in order]).withColumn("run", F.spark_partition_id()))
    key = F.struct(*order)
    firsts = keys.groupBy("run").agg(F.min(key).alias("first"))
    firsts = firsts.select("run", F.lead("first").over(W.orderBy("run")).alias("after"))
    inside = keys.withColumn("next", F.lead(key).over(W.partitionBy("run").orderBy(*order)))
    follows = F.coalesce("next", "after")
    same = (follows["a"] == F.col("a")) & (follows["b"] == F.col("b"))
    order = inside.join(F.broadcast(firsts), "run").select(F.col("conv").alias("chosen_id"), F.when(same, follows["conv"]).alias("rejected_id"))
    left = conversations.select(F.col("conv").alias("chosen_id"), F.col("turns").alias("chosen"))
    right = conversations.select(F.col("conv").alias("rejected_id"), F.col("turns").alias("rejected"))
    return order.join(left, "chosen_id").join(right, "rejected_id", "left")


def preference_rows(pairs: DataFrame) -> DataFrame:
    """Rows of ``pairs`` with n_prompt, prompt, and segments of both completions."""
    empty = F.slice(F.col("chosen"), 1, 0)
    p = pairs.withColumn("_other", F.coalesce("rejected", empty))
    m = F.least(F.size("chosen"), F.size("_other"))
    same = F.transform(F.sequence(F.lit(1), F.greatest(m, F.lit(1))), lambda i: (i <= m) & (F.get("chosen", i - 1) == F.get("_other", i - 1)))
    p = p.withColumn("_common", F.coalesce(F.array_position(F.transform(same, lambda x: F.coalesce(x, F.lit(False)).cast("int")), 0) - 1, F.lit(-1)))
    p = p.withColumn("_common", F.when(F.col("_common") < 0, m).otherwise(F.col("_common")).cast("int"))
    # one side ends inside the common turns, or there is no other side: step back to before the last assistant turn
    shorter = F.when(F.col("rejected").isNull(), F.size("chosen")).otherwise(m)
    last = F.array_max(F.transform(F.col("chosen"), lambda t, i: F.when((t["role"] == "assistant") & (i < shorter), i)))
    ends = F.col("rejected").isNull() | (F.col("_common") == F.size("chosen")) | (F.col("_common") == F.size("_other"))
    p = p.withColumn("_n", F.when(ends, F.coalesce(last, F.col("_common"))).otherwise(F.col("_common")).cast("int"))
    # an unpaired conversation keeps everything before its last assistant turn; a null rejected side has no segments
    rest = F.slice("chosen", F.col("_n") + 1, F.greatest(F.size("chosen") - F.col("_n"), F.lit(0)))
    other = F.slice("_other", F.col("_n") + 1, F.greatest(F.size("_other") - F.col("_n"), F.lit(0)))
    out = p.withColumns({
        "n_prompt": F.col("_n").cast("long"),
        "prompt": prompt_of(F.slice("chosen", 1, F.col("_n"))),
        "chosen_segments": segments(rest),
        "rejected_segments": F.when(F.col("rejected").isNotNull(), segments(other)),
    })
    return out.drop("_other", "_common", "_n", "chosen", "rejected")


def format_preferences(turns: DataFrame) -> DataFrame:
    return preference_rows(paired(cut(gathered(turns))))


def op10_chat(spark, sf_dir):
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    found = format_preferences(turns)
    text = lambda c: F.array_join(F.transform(c, lambda s: s["text"]), "")
    learnt = lambda c: F.array_join(F.transform(F.filter(c, lambda s: s["mask"] == 1), lambda s: s["text"]), "")
    return found.select(
        "chosen_id", "rejected_id", "n_prompt", "prompt",
        text("chosen_segments").alias("chosen"), F.length(learnt("chosen_segments")).cast("long").alias("chosen_learnt"),
        text("rejected_segments").alias("rejected"), F.length(learnt("rejected_segments")).cast("long").alias("rejected_learnt"),
    )


OP10_SQL = r"""
WITH t AS (
  SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, coalesce(role, ''), coalesce(text, '')) AS i,
    coalesce(role, '') AS role, coalesce(text, '') AS text
  FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL
), c AS (
  SELECT conv_id, count(*) AS n, max(CASE WHEN i = 1 THEN role || chr(1) || text END) AS head FROM t GROUP BY conv_id
), p AS (
  SELECT conv_id AS a, n AS na, lead(conv_id) OVER (PARTITION BY head ORDER BY conv_id) AS b, lead(n) OVER (PARTITION BY head ORDER BY conv_id) AS nb FROM c
), differ AS (
  SELECT p.a, min(x.i) AS i FROM p JOIN t x ON x.conv_id = p.a JOIN t y ON y.conv_id = p.b AND y.i = x.i WHERE x.role <> y.role OR x.text <> y.text GROUP BY p.a
), common AS (
  SELECT p.a, p.b, p.na, p.nb, CASE WHEN p.b IS NULL THEN p.na ELSE coalesce(differ.i - 1, least(p.na, p.nb)) END AS m FROM p LEFT JOIN differ ON differ.a = p.a
), lasts AS (
  SELECT c.a, max(t.i) - 1 AS i FROM common c JOIN t ON t.conv_id = c.a AND t.role = 'assistant' AND t.i <= c.m GROUP BY c.a
), cut AS (
  SELECT c.a, c.b, CASE WHEN c.b IS NULL THEN coalesce(lasts.i, 0) WHEN c.m = c.na OR c.m = c.nb THEN coalesce(lasts.i, c.m) ELSE c.m END AS k
  FROM common c LEFT JOIN lasts ON lasts.a = c.a
), r AS (
  SELECT conv_id, i, '<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10) AS s, CASE WHEN role = 'assistant' THEN length(text) + 10 ELSE 0 END AS learnt FROM t
)
SELECT cut.a AS chosen_id, cut.b AS rejected_id, CAST(cut.k AS BIGINT) AS n_prompt,
  coalesce(string_agg(CASE WHEN x.i <= cut.k THEN x.s END, '' ORDER BY x.i), '') AS prompt,
  coalesce(string_agg(CASE WHEN x.i > cut.k THEN x.s END, '' ORDER BY x.i), '') AS chosen,
  CAST(sum(CASE WHEN x.i > cut.k THEN x.learnt ELSE 0 END) AS BIGINT) AS chosen_learnt,
  any_value(o.rejected) AS rejected, any_value(o.learnt) AS rejected_learnt
FROM cut JOIN r x ON x.conv_id = cut.a
LEFT JOIN (
  SELECT cut.a, coalesce(string_agg(CASE WHEN y.i > cut.k THEN y.s END, '' ORDER BY y.i), '') AS rejected, CAST(sum(CASE WHEN y.i > cut.k THEN y.learnt ELSE 0 END) AS BIGINT) AS learnt
  FROM cut JOIN r y ON y.conv_id = cut.b GROUP BY cut.a
) o ON o.a = cut.a
GROUP BY cut.a, cut.b, cut.k
"""
