"""The training-data operators against brute force, and their defined cases."""

from __future__ import annotations

import bisect
import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from subpopgrid.llm import chat, decontaminate, language, packing, quality, queries, resharding, set_join, token_files, tokens, url_filter, wrappers
from tests.conftest import SF, same_rows

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [None, "", " ", "one", "two words", "a\nb  c\t d", "é" * 5, "x" * 3000, "word " * 400, "same text here now", "same text here now"]


def docs_of(spark, texts, **extra):
    rows = [(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, DOCS)
    for name in ("size", "token", "features", "id", "hash", "shard"):  # names that operators use too
        df = df.withColumn(name, F.lit("clash"))
    return df


def empty_docs(spark):
    return spark.createDataFrame([], DOCS)


def vocabulary(n, seed=0):
    r = random.Random(seed)
    return ["".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7))) for _ in range(n)]


def prose(n, seed):
    r, words = random.Random(seed), vocabulary(400)
    return " ".join(r.choice(words) for _ in range(n))


# --- tokens, files, packing ---


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet=st.sampled_from(list("ab Zé.,'!\n\t0ñß —漢")), max_size=60))
def test_cached_encoding_is_the_librarys(text):
    for name, spaced in (("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)):
        e = tokens.encoder(name, spaced)
        assert e(text) == (e.whole(text) if text else b"")


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet=st.sampled_from(list("ab Zé.,'!\n\t0ñß —漢")), max_size=40)), max_size=12))
def test_sliced_encoding_is_the_librarys(texts):
    for name, spaced in (("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)):
        got = {}
        for lo, hi, flat, counts in tokens.encoder(name, spaced).slices(pa.array(texts, pa.string()), 2):
            got |= dict(zip(range(lo, hi), np.split(flat, np.cumsum(counts)[:-1]), strict=True))
        assert [got[i].tolist() for i in range(len(texts))] == [ids_of(name, t).tolist() for t in texts]


def ids_of(name, text):
    t = Tokenizer.from_file(public_tokenizers.path(name))
    return np.array([*(t.encode(text, add_special_tokens=False).ids if text else []), 2], "<u4")


def test_token_files_round_trip(spark, tmp_path):
    path = f"file://{tmp_path}/t"
    token_files.write_tokens(docs_of(spark, ODD), path, row_group=1000)
    got = {r["doc_id"]: r for r in token_files.digest(token_files.read_tokens(spark, path)).collect()}
    at = 0
    for i, t in enumerate(ODD):
        ids = ids_of("word_bpe_49k.json", t)
        assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert token_files.lookup(spark, path, [3]).first()["ids"] == ids_of("word_bpe_49k.json", "one").tolist()


def test_token_files_of_nothing(spark, tmp_path):
    path = f"file://{tmp_path}/t"
    token_files.write_tokens(empty_docs(spark), path)
    assert token_files.digest(token_files.read_tokens(spark, path)).count() == 0


def sequential_best_fit(lengths, capacity):
    gaps, opened = [], 0
    for x in sorted(lengths, reverse=True):
        i = bisect.bisect_left(gaps, x)
        if i == len(gaps):
            opened += 1
            left = capacity - x
        else:
            left = gaps.pop(i) - x
        bisect.insort(gaps, left)
    return opened


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 32), max_size=120))
def test_sweep_equals_sequential_best_fit(lengths):
    counts = {x: lengths.count(x) for x in set(lengths)}
    runs, opened = packing.sweep(counts, 32)
    assert opened == sequential_best_fit(lengths, 32)
    used: dict[int, list] = {}
    by: dict[int, list] = {}
    for length, rank, first, offset in runs:
        by.setdefault(length, []).append((rank, first, offset))
    for length, places in by.items():
        places.sort()
        for (rank, first, offset), end in zip(places, [*(p[0] for p in places[1:]), counts[length]], strict=True):
            for k in range(end - rank):
                used.setdefault(first + k, []).append((offset, length))
    assert sum(map(len, used.values())) == len(lengths)
    for spans in used.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 32


def test_places_by_join_are_the_same(spark, monkeypatch):
    docs = docs_of(spark, [*ODD, *(prose(random.Random(i).randint(1, 90), i) for i in range(80))])
    key = lambda df: sorted((r["doc_id"], r["piece"], r["sequence_id"], r["offset"]) for r in df.collect())
    usual = key(packing.pack(packing.pieces(docs, 64), 64))
    monkeypatch.setattr(packing, "BROADCAST_LIMIT", 0)
    assert key(packing.pack(packing.pieces(docs, 64), 64)) == usual


def test_packing_places_every_piece(spark):
    texts = [*ODD, prose(2500, 3)]
    got = packing.pack(packing.pieces(docs_of(spark, texts), 64), 64).toPandas()
    for i, t in enumerate(texts):
        ids = ids_of("byte_bpe_50k.json", t)
        own = got[got.doc_id == i].sort_values("piece")
        assert own.length.sum() == len(ids) and (own.length.iloc[1:] == 64).all()
        for r in own.itertuples():
            assert r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes())
    for _, s in got.sort_values("offset").groupby("sequence_id"):
        assert (s.offset == s.length.cumsum() - s.length).all() and s.length.sum() <= 64
    assert got.sequence_id.nunique() == sequential_best_fit(got.length.tolist(), 64)
    assert packing.pack(packing.pieces(empty_docs(spark), 64), 64).count() == 0


# --- resharding ---


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 1000), min_size=1, max_size=7), st.integers(1, 7))
def test_flow_moves_the_fewest_bytes(supply, shards):
    supply = supply + [0] * max(0, shards - len(supply))
    capacity = resharding.even_capacities(sum(supply), shards) + [0] * (len(supply) - shards)
    flow = resharding.min_cost_flow(supply, capacity)
    for s, n in enumerate(supply):
        assert sum(v for (a, _), v in flow.items() if a == s) == n
    for t, n in enumerate(capacity):
        assert sum(v for (_, b), v in flow.items() if b == t) == n
    assert sum(v for (a, b), v in flow.items() if a != b) == sum(max(0, s - c) for s, c in zip(supply, capacity, strict=True))


def test_resharding(spark, tmp_path):
    texts = ODD + [prose(random.Random(i).randint(1, 80), i) for i in range(400)]
    docs = docs_of(spark, texts).select("doc_id", "text")
    old = F.when(F.col("doc_id") % 3 == 0, 0).otherwise(F.pmod("doc_id", F.lit(5)))
    path = f"file://{tmp_path}/s"
    flow = resharding.reshard(docs, old, 8, path, rewrite_all=True)
    got = resharding.read_shards(spark, path, "doc_id long, text string, _row long, _task int, shard int").toPandas()
    assert sorted(got.doc_id) == list(range(len(texts)))
    got["size"] = [len((t or "").encode()) + 16 for t in got.text]
    by = got.groupby("shard")
    assert len(by) == 8 and by["size"].sum().max() - by["size"].sum().min() <= 2 * got["size"].nlargest(2).iloc[1]
    assert all(sorted(g.slot) == list(range(len(g))) for _, g in by)
    # what stays is what the flow keeps, up to a document a block
    stays = got.merge(docs.withColumn("old", old).select("doc_id", "old").toPandas(), on="doc_id")
    kept = stays[stays.old == stays.shard]["size"].sum()
    assert kept >= sum(v for (s, t), v in flow.items() if s == t) - 8 * 3016
    # an even layout stays as it is: nothing is written
    again = f"file://{tmp_path}/again"
    one = docs_of(spark, ["abcd"] * 8).select("doc_id", "text")
    assert all(s == t for s, t in resharding.reshard(one, F.col("doc_id").cast("int"), 8, again))
    resharding.reshard(empty_docs(spark), F.lit(0), 8, f"file://{tmp_path}/none")
    assert resharding.read_shards(spark, f"file://{tmp_path}/none", "doc_id long, text string, _row long, _task int, shard int").count() == 0


def test_resharding_balances_bytes_and_renames_clashes(spark, tmp_path):
    texts = [f"{i:05}" + "x" * 19_995 for i in range(40)] + [f"short {i}" for i in range(3000)]
    docs = spark.createDataFrame([(i if i % 3 else None, t, "mine") for i, t in enumerate(texts)], "doc_id long, text string, shard string").withColumn("_Row", F.lit("row"))
    path = f"file://{tmp_path}/s"
    resharding.reshard(docs, F.when(F.col("shard") == "mine", 1), 4, path, rewrite_all=True)
    got = resharding.read_shards(spark, path, "doc_id long, text string, shard_ string, _Row_ string, _row long, _task int, shard int").toPandas()
    assert sorted(got.text) == sorted(texts) and set(got.shard_) == {"mine"} and set(got._Row_) == {"row"}
    assert all(sorted(g.slot) == list(range(len(g))) for _, g in got.groupby("shard"))
    placed = got.assign(size=[len(t) + 16 for t in got.text])
    rows, tasks = resharding.in_tasks(spark.createDataFrame(placed[["doc_id", "text", "shard"]].astype(object).where(placed[["doc_id", "text", "shard"]].notna(), None), "doc_id double, text string, shard int"), int(placed["size"].sum()), "doc_id", "text")
    each = rows.groupBy("_task").agg(F.sum(resharding.text_bytes()).alias("n")).toPandas().n
    assert tasks >= 8 and each.max() <= 2 * placed["size"].sum() / tasks + 20_016


# --- decontamination ---


def plain_smith_waterman(a, b):
    h = np.zeros((len(a) + 1, len(b) + 1), int)
    for i, x in enumerate(a, 1):
        for j, y in enumerate(b, 1):
            h[i, j] = max(0, h[i - 1, j - 1] + (decontaminate.MATCH if x == y else decontaminate.MISMATCH), h[i - 1, j] + decontaminate.GAP, h[i, j - 1] + decontaminate.GAP)
    return int(h.max())


@settings(max_examples=100, deadline=None)
@given(st.lists(st.sampled_from("abcd"), max_size=12), st.lists(st.sampled_from("abcde"), max_size=20))
def test_alignment_is_smith_waterman(item, window):
    assert decontaminate.align(item, window)[0] == plain_smith_waterman(item, window)


def test_decontamination_catches_copies_and_edits(spark):
    item = prose(40, 77)
    words = item.split()
    edited = " ".join("zzz" if i % 7 == 6 else w for i, w in enumerate(words))
    part = " ".join(words[10:24])  # a passage of fourteen words
    texts = [prose(300, 1) + " " + item + " " + prose(300, 2), item.upper() + "!", prose(100, 4) + " " + edited, prose(400, 5), *ODD, part]
    bench = spark.createDataFrame([(1, item), (1, item), (2, None), (3, ""), (4, "two words"), (5, prose(30, 91))], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r for r in decontaminate.contaminated(docs_of(spark, texts), bench).collect()}
    assert {k for k in got if k[1] != 4} == {(0, 1), (1, 1), (2, 1), (len(texts) - 1, 1)}
    assert got[0, 1]["score"] == 1.0 and (got[0, 1]["first_word"], got[0, 1]["end_word"]) == (300, 340)
    assert 0.6 < got[2, 1]["score"] < 1 and (8, 4) in got
    assert decontaminate.contaminated(empty_docs(spark), bench).count() == 0
    assert decontaminate.contaminated(docs_of(spark, texts), bench.limit(0)).count() == 0


def test_many_copies_do_not_make_seeds_common(spark):
    item = prose(20, 5)
    texts = [item] * 200 + [prose(50, 100 + i) for i in range(100)]
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert decontaminate.contaminated(docs_of(spark, texts), bench).count() == 200


def test_edited_copies_with_one_seed(spark):
    words = [f"word{i}" for i in range(20)]
    edited = []
    for i, w in enumerate(words):
        edited += [w, "foreign"] if i % 2 and i != 1 else [w]
    texts = [" ".join(edited)] * 60 + [" ".join(words[:3]) + " " + prose(30, i) for i in range(60)]
    bench = spark.createDataFrame([(1, " ".join(words))], "item_id long, text string")
    got = {r["doc_id"]: r["score"] for r in decontaminate.contaminated(docs_of(spark, texts), bench).collect()}
    assert set(got) == set(range(60)) and min(got.values()) >= decontaminate.MIN_SCORE


def test_block_size_changes_nothing(spark):
    docs, items = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    clash = docs.withColumn("item_id", F.lit("x")).withColumn("window", F.lit("x"))
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(decontaminate.contaminated(clash, items, block_bytes=8 << 20)) == key(decontaminate.contaminated(docs, items, block_bytes=1 << 10)) != []


def test_items_that_share_an_id(spark):
    items = [(1, prose(30, 71)), (1, prose(30, 72)), (None, prose(30, 73)), (None, prose(30, 74)), (2, prose(30, 75))]
    texts = [prose(40, 500 + i) + " " + t for i, (_, t) in enumerate(items)] + [prose(60, 600)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.contaminated(docs_of(spark, texts), bench).collect()
    assert sorted((r["doc_id"], str(r["item_id"]), r["score"]) for r in got) == [(i, str(k), 1.0) for i, (k, _) in enumerate(items)]


# --- set join ---


def brute_classes(texts, n, num, den):
    def sets(t):
        w = (t or "").encode().translate(set_join.UPPER).split()
        return frozenset(tuple(w[i : i + n]) for i in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)] if w else [])

    s, parent = [sets(t) for t in texts], list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(s):
        for j in range(i):
            if a and s[j] and den * len(a & s[j]) >= num * len(a | s[j]):
                x, y = root(i), root(j)
                parent[max(x, y)] = min(x, y)
    return {i: (len(a), root(i)) for i, a in enumerate(s)}


def near_copies(seed, n=60):
    r, base = random.Random(seed), prose(120, seed).split()
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(r.choice([0, 0, 1, 1, 2, 3, 5, 9])):
            w[r.randrange(len(w))] = r.choice(["qq", "rr", "ss"]) + str(r.randrange(50))
        out.append(" ".join(w[: len(w) - r.choice([0, 0, 0, 5, 20])]))
    return out


@pytest.mark.parametrize(("n", "num", "den"), [(3, 90, 100), (5, 80, 100)])
def test_set_join_equals_all_pairs(spark, n, num, den):
    shared = prose(30, 999)
    texts = [*ODD, *near_copies(1), *near_copies(2, 25), *(shared + " " + prose(15, 300 + i) for i in range(25)), "Ab C d", "aB c D", "x y", "X Y"]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in set_join.classes(docs_of(spark, texts), n, num, den).collect()}
    assert got == brute_classes(texts, n, num, den)


def test_set_join_sql(spark, duck):
    """The given tables, and a table of near copies and odd texts."""
    sql = queries.oracle_sql()["op5_ngram_jaccard"]
    same_rows(queries.queries()["op5_ngram_jaccard"](spark, SF), duck.execute(sql).df())
    df = docs_of(spark, [*ODD, *near_copies(7), "Ab C d", "aB c D", "x y", "X Y"])
    import duckdb

    con = duckdb.connect()
    con.register("documents", df.toPandas())
    same_rows(set_join.classes(df, 3, 90, 100), con.execute(sql).df())


def test_set_join_odd_ids(spark):
    df = spark.createDataFrame([(None, "a b c d"), (7, "a b c d"), (7, "a b c d"), (9, "a b c e"), (None, "p q r")], "doc_id long, text string")
    got = sorted((str(r["doc_id"]), r["n_shingles"], str(r["component_id"])) for r in set_join.classes(df, 3, 90, 100).collect())
    assert got == [("7", 2, "7"), ("7", 2, "7"), ("9", 2, "9"), ("None", 1, "None"), ("None", 2, "7")]
    assert set_join.classes(empty_docs(spark), 3, 90, 100).count() == 0


# --- quality ---


def brute_measure(t):
    w = [x for x in "".join(" " if c in quality.BLANKS else c for c in (t or "")).split(" ") if x]
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    hit = {i + k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(3)}
    lines = [x for x in (t or "").split("\n") if x.strip(quality.BLANKS)]
    return len(w), sum(map(len, w)), sum(c in quality.SYMBOLS for c in t or ""), sum(x in lines[:i] for i, x in enumerate(lines)), len(hit), len(lines)


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet=st.sampled_from(list("ab \n\t#| é")), max_size=80))
def test_base_counts(text):
    assert quality.measure(text) == brute_measure(text)


def test_quality_cases(spark):
    clean = [prose(80, i) for i in range(60)]
    junk = " ".join(w + "$$$" for w in prose(80, 500).split())
    df = docs_of(spark, [*clean, junk, *ODD, "a b " * 60])
    got = {r["doc_id"]: r for r in quality.quality(df).collect()}
    assert all(got[i]["kept"] for i in range(60)) and not got[60]["kept"] and not got[60]["base_failed"]
    assert got[61]["n_words"] == 0 and got[61]["base_failed"] and got[len(got) - 1]["base_failed"]
    kept = quality.passed(df)
    assert kept.columns == df.columns and {r["doc_id"] for r in kept.select("doc_id").collect()} == {i for i, r in got.items() if r["kept"]}
    assert quality.quality(empty_docs(spark)).count() == 0
    odd = spark.createDataFrame([(None, prose(60, 1), None, None, 1)], DOCS)
    assert quality.quality(odd).first()["kept"]


def test_two_sided_limits(spark):
    """A source that is mostly junk can't loosen its limit beyond twice its language's; clean documents stay."""
    rows = [(i, prose(80, i), "en", "clean") for i in range(200)]
    rows += [(1000 + i, " ".join(w + "$$$" if i % 2 else w for w in prose(80, 700 + i).split()), "en", "junk") for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    kept = lambda rule: {r["doc_id"] for r in quality.quality(df, rule).where("kept").collect()}
    junk = {1000 + i for i in range(1, 40, 2)}
    assert junk <= kept(quality.limits) and not junk & kept(quality.two_sided)
    assert set(range(200)) <= kept(quality.two_sided) and {1000 + i for i in range(0, 40, 2)} <= kept(quality.two_sided)
    assert quality.quality(empty_docs(spark), quality.two_sided).count() == 0


def test_sql_of_quality_and_chat(spark, duck):
    for name in ("op6_quality_rules", "quality_two_sided", "op8_preference_format"):
        same_rows(queries.queries()[name](spark, SF), duck.execute(queries.oracle_sql()[name]).df())


# --- URL filter ---


def test_url_rules_and_model(spark):
    urls = ["http://A.example.ORG/es/x", "https://example.org/en/12", "https://example.org/en/2", "https://x.org", "https://x.org/", "http://a.com/fr/1?x=/de/", "http://a.com/de/", "ftp://h?q", "nothing", None, "", "http://m.adult-x.example.net/en/99", "http://casino-win.example.net/de/4", "https://quiet-village.example.net/en/7"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("features", F.lit("clash")).withColumn("host", F.lit("clash"))
    model = url_filter.train(url_filter.labelled(spark))
    got = {r["page_id"]: r for r in url_filter.judge(df, model).collect()}
    assert [got[i]["rule"] for i in range(7)] == ["example.org/es/", "example.org/en/1", "org/", None, "org/", "com/fr/", "com/de/"]
    assert [got[i]["verdict"] for i in (0, 1, 2, 4, 5, 6)] == ["block", "block", "allow", "allow", "allow", "block"]
    assert (got[0]["host"], got[0]["path"]) == ("a.example.org", "/es/x") and (got[7]["host"], got[7]["path"]) == ("h", "")
    assert all((got[i]["host"], got[i]["path"], got[i]["verdict"]) == ("", "", "allow") for i in (8, 9, 10))
    assert [got[i]["verdict"] for i in (11, 12, 13)] == ["block", "block", "allow"]
    assert url_filter.judge(df.limit(0), model).count() == 0


def test_url_model_on_held_out_names(spark):
    unwanted = ["xxx-videos.example.com", "poker-win.example.net", "pills-cheap.example.com", "spam-seo.example.net", "adult-chat.example.com"]
    ordinary = ["morning-news.example.com", "river-museum.example.net", "open-library.example.com", "cooking-recipes.example.net", "weather-maps.example.com"]
    rows = [(f"https://{h}/en/{i}", int(h in unwanted)) for i, h in enumerate(unwanted + ordinary)]
    got = url_filter.judge(spark.createDataFrame(rows, "url string, y int"), url_filter.train(url_filter.labelled(spark)), rules=())
    assert got.where("(verdict = 'block') = (y = 1)").count() >= 9


# --- chat ---


def test_preference_pairs(spark):
    turns = [(1, 0, "user", "hi"), (1, 1, "assistant", "a long answer"), (2, 0, "user", "hi"), (2, 1, "assistant", "short"), (3, 0, "user", "other"), (3, 1, "assistant", None), (5, 0, None, "hi"), (5, 1, "assistant", "a long answer"), (None, 0, "user", "x")]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    got = sorted(chat.format_pairs(chat.pair_up(chat.gather(df))).collect(), key=lambda r: r["chosen_id"])
    first = got[0]
    assert (first["chosen_id"], first["rejected_id"], first["n_prompt"]) == (1, 2, 1) and first["prompt"] == "<|user|>\nhi\n<|end|>\n"
    for side in ("chosen", "rejected"):
        spans = [tuple(map(int, s.split("-"))) for s in first[f"{side}_mask"].split(",")]
        assert [first[f"{side}_completion"][a:b] for a, b in spans] == [("a long answer" if side == "chosen" else "short") + "\n<|end|>\n"]
    assert {r["chosen_id"] for r in got} | {r["rejected_id"] for r in got} == {1, 2, 3, 5}
    assert chat.format_pairs(chat.pair_up(chat.gather(df.limit(0)))).count() == 0
    twin = spark.createDataFrame([(c, 0, "user", "q") for c in (1, 2)] + [(c, 1, "assistant", "r") for c in (1, 2)], df.schema)
    assert chat.format_pairs(chat.pair_up(chat.gather(twin))).first()["chosen_completion"] == ""


def test_pairs_over_far_ids(spark):
    openings = {255: "q", 256: "q", 10: "hot", 5000: "hot", 90000: "hot", 7: "lone", 70000: "other"} | {100_000 + 300 * i: "many" for i in range(61)}
    rows = [(c, k, r, t) for c, o in openings.items() for k, r, t in ((0, "user", o), (1, "assistant", f"answer {c}"))]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(7)
    got = chat.format_pairs(chat.pair_up(chat.gather(df))).collect()
    pairs = {frozenset((r["chosen_id"], r["rejected_id"])): r["n_prompt"] for r in got}
    many = [c for c in sorted(openings) if openings[c] == "many"]
    expected = {frozenset(p): 1 for p in [(255, 256), (10, 5000), *zip(many[:-1:2], many[1::2], strict=True)]}
    assert pairs == expected | {frozenset((7, 70000)): 0, frozenset((90000, many[-1])): 0}


def test_other_replies(spark, duck):
    turns = [(4, 0, "user", "hi"), (4, 1, "assistant", "four"), (4, 2, "user", "bye"), (9, 0, "user", "q"), (9, 1, "assistant", "first"), (9, 2, "user", "more"), (9, 3, "assistant", "nine"), (6, 0, "user", "nobody answers"), (7, 0, "assistant", None)]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string").withColumn("turns", F.lit("clash")).withColumn("opening", F.lit("clash"))
    got = {r["chosen_id"]: r for r in chat.format_pairs(chat.other_replies(chat.gather(df))).collect()}
    assert {k: (r["rejected_id"], r["n_prompt"]) for k, r in got.items()} == {4: (7, 1), 7: (9, 0), 9: (4, 3)}
    assert got[9]["prompt"].endswith("<|user|>\nmore\n<|end|>\n") and "nine" in got[9]["chosen_completion"] and "four" in got[9]["rejected_completion"]
    assert chat.format_pairs(chat.other_replies(chat.gather(df.limit(0)))).count() == 0
    own = queries.queries()["preference_other_replies"](spark, SF)
    assert own.where("n_prompt > 0 AND prompt != ''").count() >= 0.9 * own.count() > 0
    same_rows(own, duck.execute(queries.oracle_sql()["preference_other_replies"]).df())


def test_long_and_repeated_turns(spark):
    rows = [(1, 0, "user", "q"), (1, 1, "assistant", "x" * 300_000), (2, 0, "user", "q"), (2, 1, "assistant", "y"), (2, 1, "assistant", "y")]
    got = chat.format_pairs(chat.pair_up(chat.gather(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")))).first()
    assert (got["chosen_id"], got["rejected_id"], got["n_prompt"]) == (1, 2, 1)
    assert len(got["chosen_completion"]) > 300_000 and got["rejected_completion"].count("y\n") == 2


# --- language ---


def test_conflicting_evidence_decides_short_texts(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = language.fit(docs, F.col("lang"))
    words = [w for w in docs.where("lang = 'de'").orderBy("doc_id").first()["text"].split() if w.isalpha() and 4 <= len(w) <= 6]
    rows = [(i, w, said, url) for i, w in enumerate(words[:60]) for said, url in ((None, None), ("fr", "http://a.example.fr/fr/1"))]
    df = spark.createDataFrame([(2 * i + (s is not None), *r) for i, *r in rows for s in r[1:2]], "doc_id long, text string, said string, url string")
    alone = {r["doc_id"]: r["lang_pred"] for r in language.identify(df, model).collect()}
    fused = {r["doc_id"]: r["lang_pred"] for r in language.identify(df, model, declared=F.col("said"), suffix=language.address_language(F.col("url"))).collect()}
    without_suffix = {r["doc_id"]: r["lang_pred"] for r in language.identify(df, model, declared=F.col("said")).collect()}
    assert all(alone[k] == alone[k + 1] for k in range(0, 2 * len(words[:60]), 2))
    changed = [k for k in alone if alone[k] != fused[k]]
    assert changed and all(k % 2 == 1 and fused[k] == "fr" for k in changed)
    assert len(changed) > sum(alone[k] != without_suffix[k] for k in alone)


def test_host_prior_is_smoothed_over_its_domain(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = language.fit(docs, F.col("lang"))
    texts = [r["text"] for r in docs.where("lang = 'es'").orderBy("doc_id").limit(30).collect()]
    rows = [(i, t, f"h{i}.ejemplo.es") for i, t in enumerate(texts)] + [(100, "onaen", "new.ejemplo.es"), (101, "onaen", "new.elsewhere.net")]
    scores = language.score(spark.createDataFrame(rows, "doc_id long, text string, host string"), model, {"doc_id": F.col("doc_id")} | language._inputs(None, None, None, F.col("host")))
    priors = {r["_host"]: r for r in language.host_priors(language.host_sums(scores, model["langs"]), model["langs"]).collect()}
    es = f"h_{model['langs'].index('es')}"
    assert priors["new.ejemplo.es"][es] > priors["new.elsewhere.net"][es]


def test_pages_language(spark):
    got = queries.queries()["pages_language"](spark, SF).toPandas()
    pages = spark.read.parquet(f"{SF}/pages.parquet").select("page_id", language.markup_language(F.col("html")).alias("m")).toPandas()
    both = got.merge(pages, on="page_id")
    assert len(got) == len(pages) and (both.lang_pred == both.m).mean() > 0.9


def test_language_held_out(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    even, odd = docs.where("doc_id % 2 = 0"), docs.where("doc_id % 2 = 1")
    got = language.identify(odd, language.fit(even, F.col("lang"))).join(odd.select("doc_id", "lang"), "doc_id")
    assert got.where("lang_pred = lang AND kept").count() >= 0.97 * odd.count()


def test_language_evidence_and_cases(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = language.fit(docs, F.col("lang"))
    text = docs.where("lang = 'fr'").orderBy("doc_id").first()["text"]
    df = docs_of(spark, [*ODD, text, "&&& *** ||| 123"])
    got = {r["doc_id"]: r for r in language.identify(df, model, declared=F.lit("en"), host=F.col("source")).collect()}
    assert got[11]["lang_pred"] == "fr" and got[11]["kept"]  # strong text beats a wrong declaration
    assert got[0]["lang_pred"] is None and not got[0]["kept"] and not got[1]["kept"] and not got[12]["kept"]
    kept = language.accepted(df, model, declared=F.lit("en"), host=F.col("source"))
    assert kept.columns == df.columns and {r["doc_id"] for r in kept.select("doc_id").collect()} == {i for i, r in got.items() if r["kept"]}
    assert language.identify(empty_docs(spark), model).count() == 0
    assert language.identify(docs, language.fit(empty_docs(spark), F.col("lang"))).where("kept").count() == 0
    pages = spark.read.parquet(f"{SF}/pages.parquet").limit(5)
    said = pages.select(language.address_language(F.col("url")).alias("a"), language.markup_language(F.col("html")).alias("m")).collect()
    assert all(r["m"] in ("en", "fr", "de", "es") for r in said) and all(r["a"] == r["m"] for r in said)


def test_rare_languages_are_learnt(spark):
    rare = "zażółć gęślą jaźń oraz pchnąć w tę łódź jeża lub ośm skrzyń fig " * 3
    rows = [(i, prose(40, i), "en") for i in range(400)] + [(1000 + i, None, None) for i in range(400)] + [(2000 + i, rare, "pl") for i in range(3)] + [(None, "1234 5678 9012 " * 20, "xx")] * 50
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.fit(df, F.col("lang"), sample_docs=10)
    assert model["langs"] == ["en", "pl", "xx"]
    held_out = spark.createDataFrame([(1, rare + "jeszcze raz")], "doc_id long, text string")
    assert language.identify(held_out, model, declared=F.lit("pl")).first()["lang_pred"] == "pl"


def test_many_languages_compile(spark):
    """Twelve languages: generated code stays below a method's size limit, in the query's form and the pipeline's."""
    rows = [(i, prose(30, i), f"{chr(97 + i % 12)}x", "s") for i in range(48)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    model = language.fit(df, F.col("lang"))
    spark.conf.set("spark.sql.codegen.fallback", "false")
    try:
        judged = {r["doc_id"] for r in language.identify(df, model, declared=F.col("lang"), host=F.col("source")).where("kept").collect()}
        assert {r["doc_id"] for r in language.accepted(df, model, declared=F.col("lang"), host=F.col("source")).collect()} == judged
    finally:
        spark.conf.unset("spark.sql.codegen.fallback")


# --- HTML ---

PAGE = """<!DOCTYPE html><html lang=en><head><title>T</title><style>p{}</style></head><body class="menu-open"><div class="cookie-notice">We use cookies</div><header><h1>Site</h1></header>
<nav><ul>%s</ul></nav><aside>Side</aside><div class="ad">Buy</div><article class="post"><h1>Head &amp; line</h1><p>One <b>bo</b>ld&nbsp;  word<p>Two<br>lines<script>var x="</article>"</script>
<ul><li>first<li>second</ul><form><input><label>Mail</label></form>%s</article><section id="comments"><p>Nice!</p></section><footer>&copy;</footer>"""


def page(items, more=""):
    return PAGE % ("".join(f'<li><a href="/{i}">{i}</a>' for i in items), more)


def test_wrappers_extract_main_text(spark):
    rows = [(0, "http://a.x/1", page("ab")), (1, "http://a.x/2", page("abc", "<p>Three</p>")), (2, "http://A.x/3", page("a")), (3, None, None), (4, "http://b.x/", ""), (5, "http://b.x/2", "<p>bare &lt;text&gt;<p>more"), (6, "nothing", "plain words"), (0, "http://a.x/1", page("ab"))]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("wrapper", F.lit("clash"))
    got = [(r["page_id"], r["text"], r["n_chars"]) for r in wrappers.extract(df).collect()]
    main = "Head & line\nOne bold word\nTwo lines\nfirst\nsecond"
    by = {i: t for i, t, _ in got}
    assert len(got) == 8 and by[0] == main and by[2] == main and by[1] == main + "\nThree"
    assert by[3] == "" and by[4] == "" and by[5] == "bare <text>\nmore" and by[6] == "plain words"
    assert all(n == len(t) for _, t, n in got)
    assert {r["page_id"]: r["text"] for r in wrappers.extract(df, limit=0).collect()} == by  # joined, not broadcast
    assert wrappers.extract(df.limit(0)).count() == 0


def test_pages_without_main_element(spark):
    bare = "<h1>Only here</h1><p>some text</p>"
    rows = [(0, "http://a.x/1", page("ab")), (1, "http://a.x/2", page("abc")), (2, "http://a.x/3", "<div class=ad>Buy</div>" + bare)]
    rows += [(10 + i, "http://copies.x/", bare) for i in range(4)]
    rows += [(20 + i, "http://c.x/", f"<div>Motto</div><p>text {i}</p>" + ("<blockquote>Quote</blockquote>" if i == 3 else "")) for i in range(5)]
    rows += [(30, None, page("a")), (31, "odd", "<p>plain</p>"), (32, None, "<ul><li>x</li></ul>"), (33, "", "words")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    by = {r["page_id"]: r["text"] for r in wrappers.extract(df).collect()}
    assert by[2] == "Only here\nsome text" and by[0].startswith("Head & line\n") and "Side" not in by[0]
    assert all(by[10 + i] == "Only here\nsome text" for i in range(4))
    assert all(by[20 + i] == f"text {i}" + "\nQuote" * (i == 3) for i in range(5))
    assert (by[31], by[32], by[33]) == ("plain", "x", "words")


def test_wrapper_is_union_free(spark):
    a, b = (wrappers.read(page(x, m), {}) for x, m in (("ab", ""), ("abc", "<p>Three</p>")))
    w = wrappers.expression(wrappers.infer([(a[0], list(a[1])), (b[0], list(b[1]))]))
    assert "(<li>" in w and ")+" in w and "|" not in w and "#" in w
    # a page without its own part leaves the part optional
    c = wrappers.read(page("ab").replace("<aside>Side</aside>", ""), {})
    assert "(<!aside>" in wrappers.expression(wrappers.infer([(a[0], list(a[1])), (c[0], list(c[1]))])).replace("<!aside>", "<!aside>")
