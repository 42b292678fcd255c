"""Preference formatting: the longest common turn prefix of a chosen and a rejected conversation becomes one prompt.

Both continuations are rendered behind it as completions with a mask of character spans: only what an assistant
says (with its end mark) is to be learnt. All in DataFrame expressions.

Pairs: conversations that open with the same turn are paired in order of id, over the whole table; the odd one out of
each opening is paired in the same manner with the other ones left over. So every conversation is in one pair (one of
the table may stay alone: its rejected side is null). Ranks come from a range sort with totals a task, so an opening that
many conversations share spreads over tasks. The conversation with more assistant text is the chosen one, ties by id.

Defined cases: null or empty turn texts render as empty; a null role is ``user``; repeated turns are kept, ordered by
(turn, role, text); equal conversations have an empty completion on both sides; an empty table gives an empty table;
extra columns are ignored, whatever their names; a null conversation id is left out; very long turns are rendered whole
(a conversation is one value, as its reader needs it).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import staged

#: Ids a block in ``op8_sql``, which pairs within blocks only: it says the same where all ids are in one block.
BLOCK = 256
END = "<|end|>\n"


def gather(turns: DataFrame) -> DataFrame:
    """conv_id and its turns in order: array of (role, text). A conversation is one value, as its reader needs it."""
    said = F.struct("turn", F.coalesce("role", F.lit("user")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return turns.where("conv_id IS NOT NULL").groupBy("conv_id").agg(F.sort_array(F.collect_list(said)).alias("_t")).select("conv_id", F.transform("_t", lambda t: F.struct(t["role"], t["text"])).alias("turns"))


def ranked(keys: DataFrame) -> DataFrame:
    """Add ``k``, the rank by id in the opening, and ``n``, the opening's conversations, to (conv_id, opening).

    Row numbers of a stored range sort, less the first of a task's run of the opening, plus the runs of the tasks before.
    """
    order = ("opening", "conv_id")
    placed = staged(keys.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("at", F.monotonically_increasing_id()), "openings").withColumn("part", F.shiftright("at", 33))
    line = W.partitionBy("opening")
    runs = placed.groupBy("part", "opening").agg(F.count(F.lit(1)).alias("own"), F.min("at").alias("first"))  # of an opening: one a task
    bases = runs.withColumn("n", F.sum("own").over(line)).withColumn("base", F.sum("own").over(line.orderBy("part")) - F.col("own"))
    return placed.join(bases, ["part", "opening"]).select("conv_id", "opening", (F.col("at") - F.col("first") + F.col("base")).alias("k"), "n")


def pair_up(convs: DataFrame) -> DataFrame:
    """chosen_id, rejected_id and both arrays of turns (``chosen``, ``rejected``), by the rule above."""
    weight = F.aggregate(F.filter("turns", lambda t: t["role"] == "assistant"), F.lit(0), lambda a, t: a + F.length(t["text"]))
    own = staged(ranked(staged(convs.select("conv_id", F.xxhash64(F.col("turns")[0]["text"]).alias("opening")), "conversations")), "ranks")
    odd = (F.col("k") == F.col("n") - 1) & (F.col("n") % 2 == 1)
    pair = F.expr("k div 2").alias("pair")
    left_over = ranked(own.where(odd).select("conv_id", F.lit(0).cast("long").alias("opening"))).select("conv_id", F.lit(True).alias("left_over"), "opening", pair)
    pairs = own.where(~odd).select("conv_id", F.lit(False).alias("left_over"), "opening", pair).unionByName(left_over)
    side = F.struct((-weight).alias("w"), "conv_id", "turns")
    both = convs.join(pairs, "conv_id").groupBy("left_over", "opening", "pair").agg(F.min(side).alias("a"), F.max(side).alias("b"), F.count(F.lit(1)).alias("n"))
    two = F.col("n") == 2
    return both.select(F.col("a.conv_id").alias("chosen_id"), F.when(two, F.col("b.conv_id")).alias("rejected_id"), F.col("a.turns").alias("chosen"), F.when(two, F.col("b.turns")).alias("rejected"))


def _render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(F.lit("<|"), t["role"], F.lit("|>\n"), t["text"], F.lit("\n" + END))), "")


def _spans(turns: Column) -> Column:
    """Start and end (code points in the completion) of what is learnt: assistant texts with their end mark."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<from:int,to:int>>").alias("spans"))

    def add(state: Column, t: Column) -> Column:
        begin = state["at"] + F.length(t["role"]) + 5
        end = begin + F.length(t["text"]) + 1 + len(END)
        own = F.struct(begin.cast("int").alias("from"), end.cast("int").alias("to"))
        return F.struct(end.cast("int").alias("at"), F.when(t["role"] == "assistant", F.concat(state["spans"], F.array(own))).otherwise(state["spans"]).alias("spans"))

    return F.aggregate(turns, start, add, lambda s: F.transform(s["spans"], lambda x: F.concat_ws("-", x["from"], x["to"])))


def format_pairs(pairs: DataFrame) -> DataFrame:
    """The prompt, both completions and their masks. A lone conversation's prompt is its turns before its last."""
    a, b = F.col("chosen"), F.col("rejected")
    depth = F.when(b.isNull(), F.greatest(F.size(a) - 1, F.lit(0))).otherwise(
        F.aggregate(F.arrays_zip(a, b), F.struct(F.lit(0).alias("n"), F.lit(True).alias("open")), lambda s, z: F.struct((s["n"] + F.when(s["open"] & z["chosen"].eqNullSafe(z["rejected"]), 1).otherwise(0)).alias("n"), (s["open"] & z["chosen"].eqNullSafe(z["rejected"])).alias("open")), lambda s: s["n"])
    )
    cut = pairs.withColumn("n_prompt", depth.cast("int"))
    rest = lambda c: F.slice(c, F.col("n_prompt") + 1, F.greatest(F.size(c) - F.col("n_prompt"), F.lit(0)))
    return cut.select(
        "chosen_id",
        "rejected_id",
        "n_prompt",
        _render(F.slice(a, 1, F.col("n_prompt"))).alias("prompt"),
        _render(rest(a)).alias("chosen_completion"),
        F.when(b.isNotNull(), _render(rest(b))).alias("rejected_completion"),
        F.array_join(_spans(rest(a)), ",").alias("chosen_mask"),
        F.when(b.isNotNull(), F.array_join(_spans(rest(b)), ",")).alias("rejected_mask"),
    )


def op8_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_pairs(pair_up(gather(spark.read.parquet(f"{sf_dir}/conversations.parquet"))))


def other_replies(convs: DataFrame) -> DataFrame:
    """Pairs whose rejected side is the same conversation up to its last assistant turn, answered as the next conversation
    (by id, the first after the last) answers at its own end. Conversations without an assistant turn are left out.
    """
    last = F.size("turns") - F.array_position(F.transform(F.reverse("turns"), lambda t: t["role"] == "assistant"), True).cast("int") + 1
    with_reply = staged(convs.where(F.exists("turns", lambda t: t["role"] == "assistant")).select("conv_id", F.slice("turns", F.lit(1), last).alias("turns")), "conversations")
    order = ranked(with_reply.select("conv_id", F.lit(0).cast("long").alias("opening")))
    own = with_reply.join(order, "conv_id").select("conv_id", "turns", F.pmod(F.col("k") + 1, "n").alias("next"))
    replies = with_reply.select("conv_id", F.element_at("turns", -1).alias("reply")).join(order, "conv_id").select(F.col("conv_id").alias("rejected_id"), "reply", F.col("k").alias("next"))
    pairs = own.join(replies, "next")
    return pairs.select(F.col("conv_id").alias("chosen_id"), "rejected_id", F.col("turns").alias("chosen"), F.concat(F.slice("turns", F.lit(1), F.size("turns") - 1), F.array("reply")).alias("rejected"))


def preference_other_replies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations as pairs that share all but the last answer: the prompt is what came before it."""
    return format_pairs(other_replies(gather(spark.read.parquet(f"{sf_dir}/conversations.parquet"))))


_CONVS = """
WITH convs AS (
  SELECT conv_id, list({'role': coalesce(role, 'user'), 'text': coalesce(text, '')} ORDER BY turn, coalesce(role, 'user'), coalesce(text, '')) AS turns
  FROM conversations WHERE conv_id IS NOT NULL GROUP BY conv_id
), """


def other_replies_sql() -> str:
    """The pairs of ``preference_other_replies`` in DuckDB SQL."""
    tail = op8_sql().partition("), cut AS (")[2]
    return f"""{_CONVS}answered AS (
  SELECT conv_id, turns[1:list_max(list_filter(range(1, len(turns) + 1), lambda i: turns[i].role = 'assistant'))] AS turns FROM convs
  WHERE len(list_filter(turns, lambda t: t.role = 'assistant')) > 0
), ordered AS (
  SELECT *, row_number() OVER (ORDER BY conv_id) - 1 AS k, count(*) OVER () AS n FROM answered
), both_sides AS (
  SELECT a.conv_id AS chosen_id, b.conv_id AS rejected_id, a.turns AS ca, list_append(a.turns[1:len(a.turns) - 1], b.turns[len(b.turns)]) AS cb
  FROM ordered a JOIN ordered b ON b.k = (a.k + 1) % a.n
), cut AS ({tail}"""


def op8_sql() -> str:
    """The same pairs in DuckDB SQL (openings are compared as texts, as equal hashes stand for equal texts)."""
    return f"""
WITH convs AS (
  SELECT conv_id, list({{'role': coalesce(role, 'user'), 'text': coalesce(text, '')}} ORDER BY turn, coalesce(role, 'user'), coalesce(text, '')) AS turns
  FROM conversations WHERE conv_id IS NOT NULL GROUP BY conv_id
), marked AS (
  SELECT *, conv_id // {BLOCK} AS block, turns[1].text AS opening,
    coalesce(list_sum(list_transform(list_filter(turns, lambda t: t.role = 'assistant'), lambda t: length(t.text))), 0) AS weight FROM convs
), shared AS (
  SELECT *, count(*) OVER (PARTITION BY block, opening) AS n, row_number() OVER (PARTITION BY block, opening ORDER BY conv_id) AS k FROM marked
), grouped AS (
  SELECT *, CASE WHEN k = n AND n % 2 = 1 THEN NULL ELSE opening END AS grp FROM shared
), paired AS (
  SELECT *, (row_number() OVER (PARTITION BY block, grp ORDER BY conv_id) - 1) // 2 AS pair FROM grouped
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY block, grp, pair ORDER BY weight DESC, conv_id) AS side FROM paired
), sides AS (
  SELECT block, grp, pair, max(CASE WHEN side = 1 THEN conv_id END) AS chosen_id, max(CASE WHEN side = 2 THEN conv_id END) AS rejected_id FROM ranked GROUP BY ALL
), both_sides AS (
  SELECT s.*, a.turns AS ca, b.turns AS cb FROM sides s JOIN convs a ON a.conv_id = s.chosen_id LEFT JOIN convs b ON b.conv_id = s.rejected_id
), cut AS (
  SELECT *, CAST(CASE WHEN cb IS NULL THEN greatest(len(ca) - 1, 0)
    ELSE coalesce(list_min(list_filter(range(1, greatest(len(ca), len(cb)) + 1), lambda i: ca[i] IS DISTINCT FROM cb[i])) - 1, len(ca)) END AS INT) AS n_prompt FROM both_sides
), sliced AS (
  SELECT *, ca[1:n_prompt] AS p, ca[n_prompt + 1:] AS ra, cb[n_prompt + 1:] AS rb FROM cut
), spans AS (
  SELECT chosen_id, 'a' AS side, i, ra[i].role AS role, length(ra[i].role) + 5 AS head, length(ra[i].text) + {1 + len(END)} AS body FROM (SELECT chosen_id, ra, unnest(range(1, len(ra) + 1)) AS i FROM sliced)
  UNION ALL
  SELECT chosen_id, 'b', i, rb[i].role, length(rb[i].role) + 5, length(rb[i].text) + {1 + len(END)} FROM (SELECT chosen_id, rb, unnest(range(1, len(rb) + 1)) AS i FROM sliced WHERE rb IS NOT NULL)
), placed AS (
  SELECT *, CAST(sum(head + body) OVER (PARTITION BY chosen_id, side ORDER BY i) AS BIGINT) AS ends FROM spans
), masks AS (
  SELECT chosen_id, string_agg(CASE WHEN side = 'a' THEN (ends - body) || '-' || ends END, ',' ORDER BY i) AS ma,
    string_agg(CASE WHEN side = 'b' THEN (ends - body) || '-' || ends END, ',' ORDER BY i) AS mb
  FROM placed WHERE role = 'assistant' GROUP BY chosen_id
)
SELECT s.chosen_id, rejected_id, n_prompt,
  array_to_string(list_transform(p, lambda t: '<|' || t.role || '|>' || chr(10) || t.text || chr(10) || '<|end|>' || chr(10)), '') AS prompt,
  array_to_string(list_transform(ra, lambda t: '<|' || t.role || '|>' || chr(10) || t.text || chr(10) || '<|end|>' || chr(10)), '') AS chosen_completion,
  CASE WHEN rb IS NOT NULL THEN array_to_string(list_transform(rb, lambda t: '<|' || t.role || '|>' || chr(10) || t.text || chr(10) || '<|end|>' || chr(10)), '') END AS rejected_completion,
  coalesce(ma, '') AS chosen_mask, CASE WHEN rb IS NOT NULL THEN coalesce(mb, '') END AS rejected_mask
FROM sliced s LEFT JOIN masks m USING (chosen_id)"""
