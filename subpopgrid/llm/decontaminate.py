"""Benchmark decontamination: n-gram seeds join documents to test items, Smith-Waterman alignment scores them.

1. Seeds are the word n-grams of the items (an item with fewer words is one seed). One pass over the whole texts
   finds the seeds' places, and cuts for every item a window around each run of them, an item's length wide on
   both sides.
2. A window stays if it has enough of the item's words, as a multiset, to reach the score: an exact bound, which takes the
   place of any rule on how common a seed is. So background goes unaligned, and no number of copies hides a copy.
3. Windows are aligned with their item, word by word. The score is the alignment's part of the item's own score; half
   of it is a match, and so is an alignment worth ``MIN_WORDS`` equal words, a passage of a long item.

Test items are a small table: they are sent to the executors in blocks of bounded bytes, whatever their number.

Defined cases: null or empty text or item matches nothing; repeated rows and items give the same match once a
(doc_id, item_id); the texts that share an item_id are searched each, and the best match counts; so are those of a
null item_id, reported as null; a null doc_id is reported as null; an empty table on either side gives an empty table; extra
columns are ignored; very long texts are read whole.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import merged_scan, staged, take_over

SEED_WORDS = 3
#: Bytes of item text that are searched at once. Their seeds take about fifty times as much in every worker.
BLOCK_BYTES = 1 << 20
MATCH, MISMATCH, GAP = 2, -1, -1
#: A match is an alignment worth this part of the item's own score, or so many words in a row wherever the item is long.
MIN_SCORE, MIN_WORDS = 0.5, 13
WORD = re.compile(r"\w+")
WINDOWS = "doc_id long, item_id long, at long, window string"


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


def align(item: list, window: list) -> tuple[int, int]:
    """Smith-Waterman over words: the best local score and the place in ``window`` behind its end.

    A row a word of the item, all places of the window at once; gaps along the row by a running maximum.
    """
    if not item or not window:
        return 0, 0
    codes = {w: i for i, w in enumerate(dict.fromkeys(item))}
    text = np.array([codes.get(w, -1) for w in window])
    steps = GAP * np.arange(len(window) + 1)
    row, best, end = np.zeros(len(window) + 1, np.int64), 0, 0
    for w in item:
        new = np.maximum(row + GAP, 0)
        np.maximum(new[1:], row[:-1] + np.where(text == codes[w], MATCH, MISMATCH), out=new[1:])
        row = np.maximum.accumulate(new - steps) + steps
        if (top := int(row.max())) > best:
            best, end = top, int(row.argmax())
    return best, end


def matches(best: int, item_words: int, min_score: float = MIN_SCORE) -> bool:
    return best >= MATCH * min(min_score * item_words, MIN_WORDS)


def can_match(need: Counter, item_words: int, window: list[str], min_score: float = MIN_SCORE) -> bool:
    """False if the words that item and window share are too few for any alignment to match: each match needs one."""
    least, shared, held = min(min_score * item_words, MIN_WORDS), 0, {}
    for w in window:
        if (n := need.get(w)) and (k := held.get(w, 0)) < n:
            held[w] = k + 1
            shared += 1
            if shared >= least:
                return True
    return shared >= least


def seed_table(items: list[tuple[int, str]]) -> dict[int, dict[tuple, list[tuple[int, int]]]]:
    """Seed length -> seed -> (item, item's words)."""
    out: dict = {}
    for item, text in items:
        words = words_of(text)
        n = min(SEED_WORDS, len(words))
        for i in range(len(words) - n + 1 if n else 0):
            places = out.setdefault(n, defaultdict(list))[tuple(words[i : i + n])]
            if not places or places[-1][0] != item:
                places.append((item, len(words)))
    return out


def windows(docs: DataFrame, items: list[tuple[int, str]], id_col: str = "doc_id", text_col: str = "text", min_score: float = MIN_SCORE) -> DataFrame:
    """A row for each run of seeds of an item in a document, if the words around it can match the item: these words."""
    held = docs.sparkSession.sparkContext.broadcast(({n: dict(t) for n, t in seed_table(items).items()}, {i: Counter(words_of(t)) for i, t in items}))

    def find(batches):
        import pyarrow as pa

        take_over("seeds")
        seeds, needs = held.value
        for b in batches:
            out: tuple[list, ...] = ([], [], [], [])
            for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text"), strict=True):
                words = words_of(text.as_py())
                places = defaultdict(list)
                for n, table in seeds.items():
                    found = table.keys() & set(zip(*(words[k:] for k in range(n)), strict=False))
                    if found:
                        for i in range(len(words) - n + 1):
                            if (g := tuple(words[i : i + n])) in found:
                                for item in table[g]:
                                    places[item].append(i)
                for (item, size), hits in places.items():
                    start = 0
                    for k in range(1, len(hits) + 1):
                        if k == len(hits) or hits[k] - hits[k - 1] > 2 * size:
                            lo = max(0, hits[start] - size)
                            window = words[lo : hits[k - 1] + size + SEED_WORDS]
                            if can_match(needs[item], size, window, min_score):
                                for column, v in zip(out, (doc, item, lo, " ".join(window)), strict=True):
                                    column.append(v)
                            start = k
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds, strict=True)], names=["doc_id", "item_id", "at", "window"])

    return merged_scan(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).where("text IS NOT NULL").mapInArrow(find, WINDOWS)


def score_windows(found: DataFrame, items: list[tuple[int, str]], min_score: float = MIN_SCORE) -> DataFrame:
    """doc_id, item_id, score, first and last word of the match, for windows that score enough."""
    held = found.sparkSession.sparkContext.broadcast({i: words_of(t) for i, t in items})

    def rate(batches):
        import pyarrow as pa

        for b in batches:
            out = []
            for doc, item, at, text in zip(*(b.column(c).to_pylist() for c in ("doc_id", "item_id", "at", "window")), strict=True):
                words, window = held.value[item], text.split(" ")
                best, end = align(words, window)
                score = best / (MATCH * len(words))
                if matches(best, len(words), min_score):
                    _, back = align(words[::-1], window[:end][::-1])
                    out.append((doc, item, round(score, 4), at + end - back, at + end))
            cols = list(zip(*out, strict=True)) if out else [()] * 5
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["doc_id", "item_id", "score", "first_word", "end_word"])

    return found.select("doc_id", "item_id", "at", "window").mapInArrow(rate, "doc_id long, item_id long, score double, first_word long, end_word long")


def item_blocks(benchmark: DataFrame, limit: int = BLOCK_BYTES) -> Iterator[list[tuple[int | None, str]]]:
    """The test items, one block of at most ``limit`` bytes of text after another (a single longer item is its own block).

    The driver holds one block at a time; there is at least one, if empty.
    """
    block, used = [], 0
    for r in benchmark.select(F.col("item_id").cast("long").alias("i"), F.col("text").alias("t")).where("t IS NOT NULL").distinct().orderBy("i", "t").toLocalIterator():
        size = len(r["t"].encode("utf-8", "replace"))
        if block and used + size > limit:
            yield block
            block, used = [], 0
        block.append((r["i"], r["t"]))
        used += size
    yield block


def contaminated(docs: DataFrame, benchmark: DataFrame, min_score: float = MIN_SCORE, id_col: str = "doc_id", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The best match of every (document, item) that reaches the score. The documents are read once for each block of items."""
    parts = []
    for items in item_blocks(benchmark, block_bytes):
        numbered = [(k, t) for k, (_, t) in enumerate(items)]  # ids may repeat or be null
        found = staged(windows(docs, numbered, id_col, min_score=min_score), "seed-windows")
        ids = docs.sparkSession.createDataFrame([(k, i) for k, (i, _) in enumerate(items)], "_key long, item_id long")
        scored = score_windows(found, numbered, min_score).withColumnRenamed("item_id", "_key")
        parts.append(scored.join(F.broadcast(ids), "_key").select("doc_id", "item_id", "score", "first_word", "end_word"))
    rows = reduce(DataFrame.unionByName, parts)
    best = rows.groupBy("doc_id", "item_id").agg(F.max(F.struct("score", (-F.col("first_word")).alias("neg"), "end_word")).alias("m"))
    return best.select("doc_id", "item_id", F.col("m.score").alias("score"), (-F.col("m.neg")).alias("first_word"), F.col("m.end_word").alias("end_word"))


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
