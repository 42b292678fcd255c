"""Exact set-similarity join on word n-grams with set-relation skipping, and its classes.

Texts become sets of 64-bit hashes of word n-grams. Equal sets are one class, known by its least document.

* Index lists skip by position: a set's elements are ordered by how common they are (from a mergeable count
  sketch of the whole corpus; any fixed order is exact), and only its prefix is indexed: sets as similar as asked share
  an element there, and the positions of a shared element bound the overlap that is still possible.
* Answers are derived from a similar set: each index list has a pivot, its set with the shared element
  foremost; every other set of the list is measured against the pivot only, and takes over the pivot's class. What
  is left are sets of one list but different classes; the overlaps with a common pivot bound theirs from above
  and below, which decides most such pairs; the rest are measured. No link between classes is lost.

The result is one row a document with its class, so a group of copies costs a row each, not a row a pair.

Defined cases: null or blank text has the empty set, linked with nothing; a text of fewer words than n has one
element, its whole sequence; repeated rows are one class; a null doc_id gets the class of its set, or null if alone;
an empty table gives an empty table; extra columns are ignored; very long texts are read whole.
"""

from __future__ import annotations

import math

import numpy as np
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import hold, merged_scan, staged, take_over
from .components import components

#: Counters of the sketch that orders elements (fixed size, whatever the corpus), in blocks of a row each.
SKETCH_BITS, BLOCK_BITS = 20, 16
UPPER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 300_000:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


_WORDS = _Hashes()


def _begin() -> None:
    take_over("shingles")
    hold("shingles", _WORDS.clear)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(text: str | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of the n-word windows; A-Z fold to a-z, words are split at the six ASCII blanks."""
    words = text.encode("utf-8", "surrogatepass").translate(UPPER).split() if text else ()
    if not words:
        return np.empty(0, np.uint64)
    if len(words) < n:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), seed=n + len(words))], np.uint64)
    h = np.fromiter(map(_WORDS.__getitem__, words), np.uint64, len(words))
    out = np.full(len(h) - n + 1, n, np.uint64)
    for k in range(n):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[k : len(h) - n + 1 + k])
    out.sort()
    return out[np.r_[True, out[1:] != out[:-1]]]


def signature(s: np.ndarray) -> bytes | None:
    return xxhash.xxh128_digest(s.tobytes()) if len(s) else None


def prefix_length(n: int, num: int, den: int) -> int:
    """Of n ordered elements, so many that any set at least num/den similar shares one of them."""
    return n - -(-num * n // den) + 1


def signatures(docs: DataFrame, n: int) -> DataFrame:
    """Rows of documents (doc_id, n_shingles, sig) and, with ``block`` set, this task's share of the count sketch."""

    def scan(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        _begin()
        names = ["doc_id", "n_shingles", "sig", "block", "task", "counts"]
        kinds = (pa.int64(), pa.int64(), pa.binary(), pa.int32(), pa.int32(), pa.binary())
        sketch, task = np.zeros(1 << SKETCH_BITS, np.uint32), TaskContext.get().partitionId()
        for b in batches:
            sets = [shingles(t.as_py(), n) for t in b.column("text")]
            if sets and (whole := np.concatenate(sets)).size:
                sketch += np.bincount((whole & np.uint64((1 << SKETCH_BITS) - 1)).astype(np.int64), minlength=1 << SKETCH_BITS).astype(np.uint32)
            m = len(sets)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(map(signature, sets), pa.binary()), *(pa.nulls(m, k) for k in kinds[3:])], names=names)
        blocks = sketch.reshape(-1, 1 << BLOCK_BITS)
        at = [k for k in range(len(blocks)) if blocks[k].any()]
        yield pa.RecordBatch.from_arrays([*(pa.nulls(len(at), k) for k in kinds[:3]), pa.array(at, pa.int32()), pa.array([task] * len(at), pa.int32()), pa.array([blocks[k].tobytes() for k in at], pa.binary())], names=names)

    return docs.mapInArrow(scan, "doc_id long, n_shingles long, sig binary, block int, task int, counts binary")


def merge_sketch(parts: DataFrame) -> np.ndarray:
    """Adds the tasks' counters, block by block, in two rounds; the driver gets the fixed-size sum."""

    def add(pdf):
        total = np.zeros(1 << BLOCK_BITS, np.uint64)
        for c in pdf["counts"]:
            total += np.frombuffer(c, np.uint32)
        return pdf.iloc[:1].assign(counts=np.minimum(total, 2**32 - 1).astype(np.uint32).tobytes())[["block", "task", "counts"]]

    schema = "block int, task int, counts binary"
    fan = 1 + math.isqrt(parts.select("task").distinct().count())
    once = parts.select("block", F.pmod("task", F.lit(fan)).cast("int").alias("task"), "counts").groupBy("block", "task").applyInPandas(add, schema)
    sketch = np.zeros(1 << SKETCH_BITS, np.uint32).reshape(-1, 1 << BLOCK_BITS)
    for r in once.groupBy("block").applyInPandas(add, schema).toLocalIterator():
        sketch[r["block"]] = np.frombuffer(r["counts"], np.uint32)
    return sketch.ravel()


def prefixes(docs: DataFrame, n: int, num: int, den: int, sketch: np.ndarray) -> DataFrame:
    """(id, size, sig, tokens): every document's prefix, rarest elements first."""
    held = docs.sparkSession.sparkContext.broadcast(sketch)

    def scan(batches):
        import pyarrow as pa

        _begin()
        mask = np.uint64((1 << SKETCH_BITS) - 1)
        for b in batches:
            ids, sizes, sigs, tokens = [], [], [], []
            for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text"), strict=True):
                s = shingles(text.as_py(), n)
                if len(s) and doc is not None:
                    order = np.argsort(held.value[(s & mask).astype(np.int64)], kind="stable")[: prefix_length(len(s), num, den)]
                    ids.append(doc)
                    sizes.append(len(s))
                    sigs.append(signature(s))
                    tokens.append(s[order].view(np.int64))
            lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum([len(t) for t in tokens])].astype(np.int32)), pa.array(np.concatenate(tokens) if tokens else np.empty(0, np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(sizes, pa.int64()), pa.array(sigs, pa.binary()), lists], names=["id", "size", "sig", "tokens"])

    return docs.mapInArrow(scan, "id long, size long, sig binary, tokens array<long>")


def measure(pairs: DataFrame, texts: DataFrame, n: int) -> DataFrame:
    """(a, b, overlap, size_a, size_b) of the pairs (a, b with sig_a, sig_b): texts join by id, sets meet in Python.

    Where an id stands for several texts, only that with the right signature counts.
    """
    one = pairs.join(texts.withColumnRenamed("text", "text_b"), F.col("b") == F.col("doc_id")).drop("doc_id")
    both = one.join(texts.withColumnRenamed("text", "text_a"), F.col("a") == F.col("doc_id")).drop("doc_id")

    def compare(batches):
        import pyarrow as pa

        _begin()
        last, held = None, None
        for b in batches:
            out = []
            for a, sa, ta, c, sc, tc in zip(*(b.column(x) for x in ("a", "sig_a", "text_a", "b", "sig_b", "text_b")), strict=True):
                if (key := (a.as_py(), sa.as_py())) != last:
                    own = shingles(ta.as_py(), n)
                    if signature(own) != key[1]:
                        continue
                    last, held = key, own
                other = shingles(tc.as_py(), n)
                if signature(other) == sc.as_py():
                    out.append((key[0], c.as_py(), len(np.intersect1d(held, other, assume_unique=True)), len(held), len(other)))
            cols = list(zip(*out, strict=True)) if out else [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in cols], names=["a", "b", "overlap", "size_a", "size_b"])

    return both.mapInArrow(compare, "a long, b long, overlap long, size_a long, size_b long")


def _linked(num: int, den: int) -> str:
    return f"{den} * overlap >= {num} * (size_a + size_b - overlap)"


def classes(docs: DataFrame, n: int, num: int, den: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id of every row; sets link when den * intersection >= num * union."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    scanned = staged(signatures(merged_scan(texts), n), "signatures")
    light = scanned.where("block IS NULL").select("doc_id", "n_shingles", "sig")
    reps = staged(light.where("sig IS NOT NULL").groupBy("sig").agg(F.min("doc_id").alias("rep")), "representatives")
    sketch = merge_sketch(scanned.where("block IS NOT NULL").select("block", "task", "counts"))

    # index lists of the classes; lists of one set answer nothing
    own = prefixes(texts, n, num, den, sketch).join(reps.withColumnRenamed("sig", "_sig"), (F.col("id") == F.col("rep")) & (F.col("sig") == F.col("_sig"))).select("id", "size", "sig", "tokens")
    sets = staged(own.dropDuplicates(["id", "sig"]), "prefixes")
    rows = sets.select("id", "size", F.posexplode("tokens").alias("pos", "token"))  # read from storage, cheap to repeat
    several = staged(rows.groupBy("token").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("token").alias("_token")), "lists")
    lists = staged(rows.join(several, F.col("token") == F.col("_token"), "left_semi").withColumn("band", F.floor(F.log("size") / math.log(den / num) + 1e-9)), "lists")

    # a pivot for each list and band of sizes within which no size differs too much
    foremost = F.col("pos") * (1 << 42) + F.pmod("id", F.lit(1 << 42))
    pivots = staged(lists.groupBy("token", "band").agg(F.min_by("id", foremost).alias("p"), F.min_by("size", foremost).alias("p_size"), F.min("pos").alias("p_pos"), F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("token").alias("_t"), F.col("band").alias("_b"), "p", "p_size", "p_pos"), "pivots")
    fits = lambda s, i, t, j: f"{num + den} * least({s} - {i}, {t} - {j}) >= {num} * ({s} + {t})"
    star = lists.join(pivots, (F.col("token") == F.col("_t")) & (F.col("band") == F.col("_b"))).where("id != p").where(fits("size", "pos", "p_size", "p_pos"))
    sig_of = sets.select(F.col("id").alias("_id"), F.col("sig"))
    signed = lambda pairs: pairs.join(sig_of.withColumnRenamed("sig", "sig_a"), F.col("a") == F.col("_id")).drop("_id").join(sig_of.withColumnRenamed("sig", "sig_b"), F.col("b") == F.col("_id")).drop("_id")
    measured = staged(measure(signed(star.select(F.col("p").alias("a"), F.col("id").alias("b")).distinct()), texts, n), "measured")
    links = measured.where(_linked(num, den)).select("a", "b")
    reached = staged(components(links, "a", "b"), "reached")

    # sets of one list whose classes differ: bounds from a common pivot first, then measuring
    nearest = measured.groupBy("b").agg(F.max_by("a", F.col("overlap") * (1 << 32) + F.pmod("a", F.lit(1 << 32))).alias("near"), F.max("overlap").alias("shared"))
    known = staged(lists.join(reached.withColumnRenamed("id", "_id"), F.col("id") == F.col("_id"), "left").join(nearest, F.col("id") == F.col("b"), "left").select("token", "id", "size", "pos", "band", F.coalesce("component", "id").alias("comp"), "near", "shared"), "known")
    mixed = staged(known.groupBy("token").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1")).where("c0 < c1").select(F.col("token").alias("_t")), "mixed")
    open_ = known.join(mixed, F.col("token") == F.col("_t"), "left_semi")
    x, y = (open_.select(*(F.col(c).alias(f"{c}_{s}") for c in open_.columns)) for s in "ab")
    # sets that may link differ by a band of sizes at most, so a long list meets itself band by band
    y = y.withColumn("at", F.explode(F.array(F.col("band_b") - 1, F.col("band_b"), F.col("band_b") + 1)))
    near = x.join(y, (F.col("token_a") == F.col("token_b")) & (F.col("band_a") == F.col("at")) & (F.col("comp_a") < F.col("comp_b")) & F.expr(f"{den} * least(size_a, size_b) >= {num} * greatest(size_a, size_b)") & F.expr(fits("size_a", "pos_a", "size_b", "pos_b")))
    upper = "least(shared_a, shared_b) + least(size_a - shared_a, size_b - shared_b)"
    possible = near.where(f"NOT coalesce(near_a = near_b AND {num + den} * ({upper}) < {num} * (size_a + size_b), false)")
    pairs = possible.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")).distinct()
    done = measured.select(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y"))
    rest = staged(pairs.join(done, (F.least("a", "b") == F.col("x")) & (F.greatest("a", "b") == F.col("y")), "left_anti"), "rest")
    if rest.take(1):
        late = staged(measure(signed(rest), texts, n), "late").where(_linked(num, den)).select("a", "b")
        if late.take(1):
            reached = staged(components(links.unionByName(late), "a", "b"), "reached")

    named = staged(reps.join(reached, F.col("rep") == F.col("id"), "left").select(F.col("sig").alias("_sig"), F.coalesce("component", "rep").alias("component")), "named")
    out = light.join(named, F.col("sig") == F.col("_sig"), "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


WORDS, NUM, DEN = 3, 90, 100


def op5_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(spark.read.parquet(f"{sf_dir}/documents.parquet"), WORDS, NUM, DEN)


def op5_sql() -> str:
    """The same classes in DuckDB SQL: all pairs that share a shingle, then the closure of the links.

    For small tables: it meets every pair of a shingle's documents, which the operator does not.
    """
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    gram = " || ' ' || ".join(f"words[i{f' + {k}' if k else ''}]" for k in range(WORDS))
    return rf"""
WITH RECURSIVE texts AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '[^\x20\x09-\x0D]+') AS words FROM documents
), sets AS MATERIALIZED (
  SELECT doc_id, CASE WHEN len(words) = 0 THEN [] WHEN len(words) < {WORDS} THEN [array_to_string(words, ' ')]
    ELSE list_distinct(list_transform(range(1, len(words) - {WORDS - 2}), lambda i: {gram})) END AS grams FROM texts
), rows AS MATERIALIZED (
  SELECT doc_id, len(grams) AS size, unnest(grams) AS gram FROM sets
), links AS MATERIALIZED (
  SELECT x.doc_id AS a, y.doc_id AS b FROM rows x JOIN rows y ON x.gram = y.gram AND x.doc_id <> y.doc_id
  GROUP BY x.doc_id, y.doc_id, x.size, y.size HAVING {DEN} * count(*) >= {NUM} * (x.size + y.size - count(*))
), reached AS (
  SELECT doc_id, doc_id AS other FROM sets UNION SELECT r.doc_id, l.b FROM reached r JOIN links l ON r.other = l.a
)
SELECT s.doc_id, CAST(len(s.grams) AS BIGINT) AS n_shingles, c.component_id
FROM sets s JOIN (SELECT doc_id, min(other) AS component_id FROM reached GROUP BY doc_id) c ON s.doc_id = c.doc_id"""
