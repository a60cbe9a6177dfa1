"""The pipeline on a small table, against a plain version of its filtering stages."""

import collections
import re

import corpus_pipeline
from axisgrove.llm import decontaminate
from pyspark.sql import functions as F

from tests.llm.test_operators import brute_components, brute_rules, brute_windows, words

SF = "/root/testdata/sf0.001"


def test_pipeline(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF).cache()
        seen[name] = out
        if name != "sharded":
            assert out.columns == corpus_pipeline.COLUMNS
        docs = out
    first = seen["quality_rules"].count()
    assert 0 < seen["near_duplicates"].count() <= first
    left = decontaminate.contaminated_words(seen["without_benchmark"], spark.read.parquet(f"{SF}/benchmark.parquet"), ["doc_id"])
    assert left.filter(F.size("hits") > 0).isEmpty()
    assert seen["mixed"].groupBy("doc_id").count().agg(F.max("count")).head()[0] <= 2
    assert seen["sharded"].count() == seen["mixed"].count() and seen["sharded"].select("shard").distinct().count() == 16
    assert corpus_pipeline.run(spark, SF).count() == seen["sharded"].count()


def plain_quality(rows):
    """(doc_id, text, lang, source) after the line rules."""
    norm = lambda x: re.sub("[0-9]+", "0", re.sub(r"[\x20\x09-\x0D]+", " ", x).strip(" ")).lower()
    filled = lambda t: [x for x in t.split("\n") if words(x)]
    hosts = collections.defaultdict(set)
    for _, t, _, s in rows:
        hosts[s].add(t or "")
    common = {s: {x for x, n in collections.Counter(x for t in texts for x in {norm(y) for y in filled(t)}).items() if n > 20 and 1000 * n > 20 * len(texts)} for s, texts in hosts.items()}
    out = []
    for (i, t, lang, s), failed in zip(rows, [v[5] for v in each_rules(rows)], strict=True):
        gone = [x for x in filled(t or "") if norm(x) in common[s]]
        n = len(words(t))
        left = n - sum(len(words(x)) for x in gone)
        if not failed and left >= 20 and 10 * left >= 3 * n:
            out.append((i, "\n".join(x for x in t.split("\n") if not gone or norm(x) not in common[s]), lang, s))
    return out


def each_rules(rows):
    return [brute_rules([r])[r[0]] for r in rows]


def plain_single(rows):
    """One document of each group of similar ones, the one of smallest id."""
    sets, label = brute_components(rows, corpus_pipeline.SHINGLE, corpus_pipeline.SIMILAR)
    best = {}
    for k, v in label.items():
        best[v] = min(best.get(v, k), k, key=lambda x: rows[x][0])
    return [r for k, r in enumerate(rows) if not sets[k] or best[label[k]] == k]


def test_filtering_stages_against_a_plain_version(spark):
    """Rules, near duplicates and benchmark windows by sets and counters: the same documents and texts."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = sorted(map(tuple, docs.select("doc_id", "text", "lang", "source").collect()))
    items = list(map(tuple, spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()))
    assert len({r[0] for r in rows}) == len(rows)
    ruled = plain_quality(rows)
    single = plain_single(ruled)
    hits = brute_windows(single, items)
    clean = [r for r in single if not hits[r[0]][1]]
    assert len(rows) > len(ruled) > len(single) > len(clean) > 0
    for (name, stage), expected in zip(corpus_pipeline.STAGES, (ruled, single, clean)):
        docs = stage(spark, docs, SF).cache()
        assert sorted(map(tuple, docs.collect())) == sorted((*r, len(r[1])) for r in expected), name


def test_mix_and_shards_lose_nothing(spark):
    """Every copy that the mix makes is a document as it was, every sharded row one of them, and run() gives the same rows."""
    docs, kept = spark.read.parquet(f"{SF}/documents.parquet"), []
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF).cache()
        kept.append(collections.Counter(map(tuple, docs.select(*corpus_pipeline.COLUMNS).collect())))
    assert set(kept[3]) <= set(kept[2]) and kept[4] == kept[3]
    target, size = collections.Counter(), collections.Counter()
    for r, n in kept[2].items():
        size[r[3]] += n * len(words(r[1]))
    for r, n in kept[3].items():
        target[r[3]] += n * len(words(r[1]))
    biggest = max(len(words(r[1])) for r in kept[2])
    assert all(target[s] <= 2 * size[s] + biggest for s in size)
    assert abs(sum(target.values()) - 1.5 * sum(size.values())) <= biggest * len(size)
    run = corpus_pipeline.run(spark, SF)
    assert collections.Counter(map(repr, map(tuple, run.collect()))) == collections.Counter(map(repr, map(tuple, docs.select(*run.columns).collect())))


def test_mix_moves_no_text(spark, monkeypatch):
    """No text goes through Python or is moved to meet what its source lacks, and words are counted as in ``with_sizes``."""
    texts = [None, "", " ", "\n\t a", "a", "a ", " a  b\x0b\x0cc\r\n", "ä\u00a0b \u3000c 😀 d", "x\x1cy\x85z", " " * 5000, "x " * 5000]
    docs = spark.createDataFrame([(i, t, "en", f"s{i % 3}", 0) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    plain = {r["doc_id"]: r["size"] for r in corpus_pipeline.mixing.with_sizes(docs).collect()}
    assert {r["doc_id"]: r["n"] for r in docs.select("doc_id", corpus_pipeline.mixing.word_count(F.col("text")).alias("n")).collect()} == plain
    counted = []
    monkeypatch.setattr(corpus_pipeline.mixing, "with_sizes", lambda *a, **b: counted.append(a))
    held = spark.range(4000).selectExpr("id AS doc_id", "array_join(transform(sequence(1, 20), i -> md5(concat(id, '-', i))), ' ') AS text", "'en' AS lang", "concat('s', id % 3) AS source", "id AS n_chars")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "256k")
    try:
        plan = corpus_pipeline.mixed(spark, held, SF)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert not counted and "InArrow" not in plan and "SortMergeJoin" not in plan


def test_pipeline_edges(spark, tmp_path):
    """Nulls in every column, empty and long texts, repeated rows and ties go through all stages; an empty table stays empty."""
    long = " ".join(f"w{i % 997}x{i % 89}" for i in range(30000))
    plain = " ".join(f"word{i}" for i in range(60))
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    rows = [(None, None, None, None, None), (1, None, "en", "a", 0), (2, "", "en", None, 0), (3, long, None, "a", None), (4, plain, "en", "a", 1), (4, plain, "en", "a", 1), (5, plain, "en", "b", 1), (None, plain + " more", None, None, None), (6, "few words", "en", "b", 1)]
    docs = spark.createDataFrame(rows, schema)
    (spark.createDataFrame([(1, " ".join(f"other{i}" for i in range(20))), (2, None)], "item_id long, text string")).write.parquet(f"{tmp_path}/benchmark.parquet")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    # Only the long text and one of the copies are left; each is taken at most twice.
    assert {r["text"] for r in got} <= {long, plain} and all(0 <= r["shard"] < 16 for r in got)
    taken = docs.filter("false")
    for name, stage in corpus_pipeline.STAGES:
        taken = stage(spark, taken, str(tmp_path))
        assert taken.count() == 0, name
