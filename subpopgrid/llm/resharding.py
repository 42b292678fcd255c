"""Minimum-cost-flow resharding: the fewest bytes leave their shard, then the affected shards are rewritten.

* Old shard sizes and new capacities form a transport network: moving a byte costs 1, keeping it 0. Successive
  shortest paths solve it on the driver; the network has a node a shard, whatever the data's size.
* A shard's documents form a line ordered by (size descending, doc_id). The flow cuts the line at byte offsets into
  blocks, one a target; the part that stays comes first, so the moved blocks are the small documents and a
  target misses its capacity by a few small documents at most. A block is known by its first document, so every row
  finds its block by comparison with the cuts of its shard: texts are not joined.
* Only shards that lose or gain rows are written, by tasks of equal bytes: a bounded sample of rows, drawn with
  chances in proportion to their bytes, gives the bounds of the tasks' ranges, so neither a shard of few long texts
  nor one of many short ones is a hot task.

Defined cases: null text has no bytes but the overhead; null old shard counts as shard 0; rows with equal doc_id and
size stay together; null doc_id sorts first; an empty table gives an empty table; extra columns travel along, those named
like the operator's own (``shard``, ``_old``, ``_row``, ``_task``) under their names with underscores added; a very
long text is one row of one task, whose range then holds little else; repeated rows are placed each (those equal in id and
text are written by one task).
"""

from __future__ import annotations

from collections import deque

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh, new_path, with_prefix_sums

OVERHEAD = 16
#: Bytes of text that a writing task takes, the most such tasks, and the sampled rows that set their bounds.
TASK_BYTES, MOST_TASKS, SAMPLE_ROWS = 32 << 20, 250_000, 1_000_000
OWN = ("shard", "_old", "_row", "_task")


def text_bytes(text: str = "text") -> Column:
    return F.coalesce(F.octet_length(F.col(text)), F.lit(0)).cast("long") + OVERHEAD


def even_capacities(total: int, shards: int) -> list[int]:
    return [total // shards + (k < total % shards) for k in range(shards)]


def min_cost_flow(supply: list[int], capacity: list[int]) -> dict[tuple[int, int], int]:
    """Bytes from each old shard to each new one, least bytes moved. Sums must agree.

    Shortest paths by label correction on the residual network; staying (cost 0) first, then moves (cost 1).
    """
    if sum(supply) != sum(capacity):
        raise ValueError("supply and capacity differ in sum")
    old, new = len(supply), len(capacity)
    source, sink, n = old + new, old + new + 1, old + new + 2
    head, room, cost, out = [], [], [], [[] for _ in range(n)]

    def arc(a: int, b: int, most: int, price: int) -> None:
        for x, y, m, p in ((a, b, most, price), (b, a, 0, -price)):
            out[x].append(len(head))
            head.append(y)
            room.append(m)
            cost.append(p)

    for s, bytes_ in enumerate(supply):
        arc(source, s, bytes_, 0)
    for t, bytes_ in enumerate(capacity):
        arc(old + t, sink, bytes_, 0)
    first_move = len(head)
    for s in range(old):
        for t in range(new):
            arc(s, old + t, sum(supply), int(s != t))
    while True:
        dist, via, queue, waiting = [None] * n, [-1] * n, deque([source]), [False] * n
        dist[source] = 0
        while queue:
            x = queue.popleft()
            waiting[x] = False
            for e in out[x]:
                y = head[e]
                if room[e] and (dist[y] is None or dist[x] + cost[e] < dist[y]):
                    dist[y], via[y] = dist[x] + cost[e], e
                    if not waiting[y]:
                        waiting[y] = True
                        queue.append(y)
        if dist[sink] is None:
            break
        path, x = [], sink
        while x != source:
            path.append(via[x])
            x = head[via[x] ^ 1]
        step = min(room[e] for e in path)
        for e in path:
            room[e] -= step
            room[e ^ 1] += step
    flow = {}
    for e in range(first_move, len(head), 2):
        if room[e ^ 1]:
            flow[head[e ^ 1], head[e] - old] = room[e ^ 1]
    return flow


def plan_blocks(docs: DataFrame, old_shard: Column, shards: int, id_col: str = "doc_id", text_col: str = "text") -> tuple[list[tuple], dict]:
    """Cuts (old shard, negative size, doc_id, target) in line order, and the flow they carry out."""
    light = docs.select(F.coalesce(old_shard, F.lit(0)).cast("long").alias("old"), F.col(id_col).cast("long").alias("doc_id"), text_bytes(text_col).alias("size")).withColumn("neg", -F.col("size"))
    sizes = {r["old"]: r["n"] for r in light.groupBy("old").agg(F.sum("size").alias("n")).collect()}  # a row a shard
    if not sizes:
        return [], {}
    supply = [sizes.get(s, 0) for s in range(max(max(sizes) + 1, shards))]
    flow = min_cost_flow(supply, even_capacities(sum(supply), shards))
    ends: dict[int, list[tuple[int, int]]] = {}
    for (s, t), n in sorted(flow.items(), key=lambda x: (x[0][0], x[0][0] != x[0][1], x[0][1])):
        line = ends.setdefault(s, [])
        line.append((t, (line[-1][1] if line else 0) + n))
    line = with_prefix_sums(light, "old", [F.col("neg"), F.col("doc_id")], "size", "before")
    spark = docs.sparkSession
    blocks = spark.createDataFrame([(s, t, (v[i - 1][1] if i else 0), end) for s, v in ends.items() for i, (t, end) in enumerate(v)], "old long, target int, lo long, hi long")
    middle = F.col("before") + F.floor(F.col("size") / 2)
    cuts = line.join(F.broadcast(blocks), "old").where((middle >= F.col("lo")) & (middle < F.col("hi"))).groupBy("old", "target").agg(F.min(F.struct("neg", "doc_id")).alias("at")).collect()  # at most a row a block
    low = -(1 << 63)
    return sorted(((c["old"], c["at"]["neg"], low if c["at"]["doc_id"] is None else c["at"]["doc_id"], c["target"]) for c in cuts), key=lambda c: c[:3]), flow


def assign(docs: DataFrame, old_shard: Column, cuts: list[tuple], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Add ``_old`` and ``shard``: each row compares its (size, doc_id) with the cuts of its old shard."""
    spark = docs.sparkSession
    table = spark.createDataFrame(cuts, "_old long, neg long, id long, target int").groupBy("_old").agg(F.sort_array(F.collect_list(F.struct("neg", "id", "target"))).alias("_cuts"))
    key = F.struct((-text_bytes(text_col)).alias("neg"), F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))).alias("id"))
    found = F.element_at(F.filter("_cuts", lambda c: F.struct(c["neg"], c["id"]) <= key), -1)["target"]
    return docs.withColumn("_old", F.coalesce(old_shard, F.lit(0)).cast("long")).join(F.broadcast(table), "_old", "left").withColumn("shard", F.coalesce(found, F.col("_cuts")[0]["target"])).drop("_cuts")


def in_tasks(placed: DataFrame, total: int, id_col: str, text_col: str) -> tuple[DataFrame, int]:
    """Add ``_task``: ranges of (shard, id, hash of the text) that hold equal bytes, and their number.

    A row is sampled with a chance of its bytes over ``unit`` (surely from there on) and then stands for ``unit`` (or its)
    bytes. Each shard's bounds are broadcast as blocks, so a row finds its range in two short searches.
    """
    spark = placed.sparkSession
    tasks = min(MOST_TASKS, max(2 * spark.sparkContext.defaultParallelism, total // TASK_BYTES + 1))
    unit = max(1, total // min(SAMPLE_ROWS, 64 * tasks))
    key = (F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))).alias("id"), F.xxhash64(text_col).alias("tie"))
    light = placed.select("shard", *key, text_bytes(text_col).alias("size"))
    drawn = F.pmod(F.xxhash64("tie", "id", "shard"), F.lit(unit)) < F.col("size")
    sample = sorted((r["shard"], r["id"], r["tie"], max(unit, r["size"])) for r in light.where(drawn).toLocalIterator())
    step, at, last, bounds = sum(r[3] for r in sample) / tasks, 0, 0, {}
    for shard, id_, tie, weight in sample:
        if int(at / step) > last:
            last = int(at / step)
            bounds.setdefault(shard, []).append((id_, tie))
        at += weight
    width = 64
    rows, before = [], 0
    for shard in sorted({r[0] for r in sample}):
        own = bounds.get(shard, [])
        rows.append((shard, before, own[::width], [own[i : i + width] for i in range(0, len(own), width)]))
        before += len(own)
    pair = "array<struct<id:long,tie:long>>"
    table = spark.createDataFrame(rows, f"shard int, _first int, _tops {pair}, _blocks array<{pair}>")
    upto = lambda bounds_: F.size(F.filter(bounds_, lambda b: F.struct(b["id"], b["tie"]) <= F.struct(*key)))
    block = upto(F.col("_tops")) - 1
    inside = F.when(block < 0, 0).otherwise(block * width + upto(F.coalesce(F.get("_blocks", block), F.array().cast(pair))))
    found = placed.join(F.broadcast(table), "shard", "left").withColumn("_task", (F.coalesce(F.col("_first"), F.lit(0)) + F.coalesce(inside, F.lit(0))).cast("int"))
    return found.drop("_first", "_tops", "_blocks"), before + 1


def reshard(docs: DataFrame, old_shard: Column, shards: int, path: str, rewrite_all: bool = False, id_col: str = "doc_id", text_col: str = "text") -> dict:
    """Rewrite the affected shards below ``path`` (folders ``shard=k``, rows by id with their position ``_row``).

    ``rewrite_all`` writes unaffected shards too (a first layout). Returns the flow.
    """
    docs = docs.select(F.coalesce(old_shard, F.lit(0)).cast("long").alias("_old"), *(F.col(f"`{c}`").alias(fresh(c, [*OWN, *docs.columns]) if c.lower() in OWN else c) for c in docs.columns))
    cuts, flow = plan_blocks(docs, F.col("_old"), shards, id_col, text_col)
    if not cuts:
        docs.drop("_old").withColumn("_row", F.lit(0).cast("long")).withColumn("_task", F.lit(0)).withColumn("shard", F.lit(0)).limit(0).write.partitionBy("shard").parquet(path)
        return flow
    placed = assign(docs, F.col("_old"), cuts, id_col, text_col).drop("_old")
    if not rewrite_all:
        touched = sorted({k for (s, t) in flow if s != t for k in (s, t) if k < shards})
        placed = placed.where(F.col("shard").isin(touched))
    numbered, tasks = in_tasks(placed, sum(flow.values()), id_col, text_col)
    lined = numbered.repartitionById(tasks, "_task").sortWithinPartitions("shard", id_col).withColumn("_row", F.monotonically_increasing_id())
    lined.write.option("compression", "zstd").partitionBy("shard").parquet(path)
    return flow


def read_shards(spark: SparkSession, path: str, schema) -> DataFrame:
    """The rewritten rows with ``slot``, their gapless position in the shard. One total a task and shard is gathered."""
    table = spark.read.schema(schema).parquet(path)
    pieces = table.groupBy("shard", "_task").agg(F.min("_row").alias("first"), F.count(F.lit(1)).alias("n")).collect()
    bases, seen = [], {}
    for r in sorted(pieces, key=lambda r: (r["shard"], r["_task"])):
        bases.append((r["shard"], r["_task"], seen.get(r["shard"], 0) - r["first"]))
        seen[r["shard"]] = seen.get(r["shard"], 0) + r["n"]
    base = spark.createDataFrame(bases, "shard int, _task int, _shift long")
    return table.join(F.broadcast(base), ["shard", "_task"]).withColumn("slot", F.col("_row") + F.col("_shift")).drop("_row", "_task", "_shift")


SHARDS = 40


def op3_flow_resharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, laid out by source in as many old shards, into 40 shards of equal bytes."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    path = new_path(spark, "shards")
    reshard(docs, F.pmod(F.crc32(F.col("source").cast("binary")), F.lit(SHARDS)), SHARDS, path, rewrite_all=True)
    rows = read_shards(spark, path, "doc_id long, text string, _row long, _task int, shard int")
    return rows.select(
        "doc_id",
        text_bytes().alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        F.lit("bytes").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )
