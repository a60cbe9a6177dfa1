"""Operators of the corpus side against brute force on small frames with nulls, empty and long texts, ties and repeated rows."""

import collections
import hashlib
import html
import random
import re
import zlib

import numpy as np
import pytest
import regex
from pyspark.sql import functions as F

from axisgrove.llm import decontaminate, html_text, jaccard_join, kd_sharding, line_rules, mixing, personal_data, quotations, suffix_dedup, url_filter
from axisgrove.llm.components import components

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(5)
    text = lambda n: " ".join(rng.choice(WORDS) + str(rng.randint(0, 40)) for _ in range(n))
    base = [text(rng.randint(30, 120)) for _ in range(30)]
    out = [(i, t, "en", f"s{i % 3}", len(t)) for i, t in enumerate(base)]
    out += [(100 + i, base[i], "en", "s0", 1) for i in range(5)]  # exact copies
    out += [(200 + i, base[i] + " tail words here", "en", "s1", 1) for i in range(5, 10)]  # near copies
    shared = text(30)
    out += [(300 + i, text(20) + " " + shared + " " + text(20), "en", "s2", 1) for i in range(4)]
    out += [(400, None, None, None, None), (401, "", "en", "s1", 0), (402, "one two", "en", "s1", 7), (None, text(40), "en", None, 3), (403, "word " * 3000, "en", "s1", 15000)]
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").cache()


@pytest.fixture(scope="module")
def empty(docs):
    return docs.filter("false")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def test_mixing(docs, rows, empty):
    sized = mixing.with_sizes(docs)
    got = mixing.pareto_mix(sized.withColumn("target", F.lit("clash"))).collect()
    assert len(got) == len(rows)
    total = sum(len(words(r[1])) for r in rows)
    by = collections.defaultdict(list)
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"]
        by[r["source"]].append(r)
    assert abs(sum(v[0]["target"] for v in by.values()) - 1.5 * total) < 1e-6 * total
    for v in by.values():
        assert v[0]["target"] <= 2 * v[0]["source_size"] + 1e-9
        assert abs(sum(r["taken"] for r in v) - v[0]["target"]) <= max(r["size"] for r in v)
    again = mixing.pareto_mix(sized.repartition(5)).collect()
    assert sorted(map(str, [(r["doc_id"], r["size"], r["taken"]) for r in got])) == sorted(map(str, [(r["doc_id"], r["size"], r["taken"]) for r in again]))
    assert mixing.pareto_mix(mixing.with_sizes(empty)).count() == 0


def test_importance_gives_unequal_shares(spark):
    sized = spark.range(2000).selectExpr("id AS doc_id", "'a' AS source", "10L AS size", "IF(id % 2 = 0, 3.0D, 1.0D) AS w")
    got = mixing.pareto_mix(sized, share=0.4, importance="w").groupBy((F.col("doc_id") % 2).alias("odd")).agg(F.sum("taken").alias("t")).collect()
    taken = {r["odd"]: r["t"] for r in got}
    assert abs(sum(taken.values()) - 8000) <= 10 and 2.4 < taken[0] / taken[1] < 3.7


def brute_suffix(rows, length=100):
    seen, out = set(), {}
    for i, t in sorted(rows, key=lambda r: (r[0] is None, r[0])):
        b = (t or "").encode()
        hit = np.zeros(len(b), bool)
        for s in range(len(b) - length + 1):
            if b[s : s + length] in seen:
                hit[s : s + length] = True
            seen.add(b[s : s + length])
        edges = np.diff(np.concatenate([[0], hit.astype(int), [0]]))
        out[i] = (len(b), int(hit.sum()), int((edges == 1).sum()), hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~hit])).hexdigest())
    return out


def test_suffix_dedup(docs, rows, empty, monkeypatch):
    expected = brute_suffix([(r[0], r[1]) for r in rows])
    for crowded in (20_000, 1):
        monkeypatch.setattr(suffix_dedup, "CROWDED", crowded)
        got = suffix_dedup.without_repeats(docs, ["doc_id"]).collect()
        assert len(got) == len(rows)
        for r in got:
            removed = [s["stop"] - s["start"] for s in r["removed"]]
            assert (r["n_bytes"], sum(removed), len(removed), hashlib.sha256(bytes(r["kept"])).hexdigest()) == expected[r["doc_id"]]
    assert suffix_dedup.without_repeats(empty, ["doc_id"]).count() == 0


def test_suffix_dedup_repeated_row_is_one_document(spark):
    t = "".join(random.Random(1).choices("abcdefgh", k=300))
    got = suffix_dedup.without_repeats(spark.createDataFrame([(1, t), (1, t), (2, t)], "doc_id long, text string"), ["doc_id"]).collect()
    assert sorted((r["doc_id"], len(r["kept"])) for r in got) == [(1, 300), (1, 300), (2, 0)]


def test_quotations(spark):
    rows = [(1, 0, "a", "Hello there\nfriend\n\nSecond par"), (1, 1, "b", "> hello  THERE\n> friend\nI agree"), (1, 2, "a", ">> Hello there\n>> friend\n> I agree\nok"), (1, 3, "c", "> Second par\n\nyes"), (2, 0, "a", None), (2, 1, None, ""), (None, 1, "x", "> q"), (1, 3, "c", "> Second par\n\nyes")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("thread", F.lit("clash"))
    got = quotations.in_reply_order(quotations.linked(df)).collect()
    assert len(got) == 8
    by = {(r["conv_id"], r["turn"]): r for r in got}
    assert by[1, 1]["reply_to"] == 0 and by[1, 2]["reply_to"] == 1 and by[1, 2]["thread"] == 0 and by[1, 2]["depth"] == 2
    assert by[1, 2]["own_text"] == "ok" and by[1, 3]["n_linked"] >= 1 and by[None, 1]["n_linked"] == 0
    assert quotations.linked(df.filter("false")).count() == 0


def test_html_text(spark):
    page = '<html><head><title>T</title><style>p{}</style></head><body><nav><ul><li><a href=/a>Menu</a></li></ul></nav><div class="cookie-notice"><p>We use cookies. Accept?</p></div><article><h1>Big  &amp; news</h1><p>First paragraph, with some words in it. And&nbsp;more.<p>Second paragraph follows here, quite long enough to be text.<script>var t="</p>";</script></p></article><div class="comments"><div class="comment"><p>I like this article. Great!</p></div></div><aside><h3>More</h3><p>Other story.</p></aside><footer>&copy; site</footer></body></html>'
    rows = [(1, "u", page), (2, "u", None), (3, None, ""), (4, "u", "<p>" * 3000 + "x"), (1, "u", page), (5, "u", "<!-- open " + "<b " * 50)]
    got = {r["page_id"]: r["main_text"] for r in html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == "Big & news\nFirst paragraph, with some words in it. And more.\nSecond paragraph follows here, quite long enough to be text."
    assert got[2] == "" and got[3] == "" and got[5] == ""
    pages, labels = html_text.labelled_pages(60, seed=77)
    p, _ = html_text.default_model().marginals(html_text.Forest(pages))
    assert ((p > 0.5) == np.concatenate(labels)).mean() > 0.93


def test_marginals_by_enumeration():
    import itertools

    page = html_text.Page("<div class=ad>x<p>y</p></div><article><p>z z z.</p></article>")
    model = html_text.TreeModel()
    rng = np.random.default_rng(1)
    model.unary, model.pair = rng.normal(size=len(model.unary)), rng.normal(size=model.pair.shape)
    f = html_text.Forest([page])
    score = (f.x @ model.unary).astype(float)
    total, mass = 0.0, np.zeros(len(score))
    for y in itertools.product((0, 1), repeat=len(score)):
        w = np.exp(sum(score[i] * y[i] for i in range(len(y))) + sum(model.pair[f.edge[i], y[f.parent[i]], y[i]] for i in range(1, len(y))))
        total, mass = total + w, mass + w * np.array(y)
    assert np.allclose(model.marginals(f)[0], mass / total)


def luhn(digits):
    return sum(x if i % 2 == 0 else x * 2 - 9 * (x > 4) for i, x in enumerate(int(c) for c in reversed(digits))) % 10 == 0


def brute_spans(t):
    out = []
    for kind, p in {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}.items():
        for m in re.finditer(p, t or ""):
            d = re.sub("[^0-9]", "", m[0])
            if {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 16 <= len(d) <= 19 and luhn(d), "phone": 8 <= len(d) <= 15}[kind]:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def test_personal_data(spark):
    rng = random.Random(8)
    made = ["".join(rng.choice("a1.+@- 4é_(") for _ in range(60)) for _ in range(150)]
    fixed = ["a@b.c@d.e x@y.z", "a@b.c_d@e.f", "1.2.3.4.5.6.7.8 300.1.1.1 001.2.3.4", "4111 1111 1111 1111 x 4111-1111-1111-1111-5", "+1 (743) 555-3824 +49.30.1234567-", None, "", "9" * 20000, "1 " * 9000, "x@" + "a." * 9000 + "b", "😀 a@b.co"]
    texts = fixed + made
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = personal_data.personal_data(df, ["doc_id"]).select("doc_id", personal_data.listed(F.col("base")).alias("b"), personal_data.listed(F.col("spans")).alias("s")).collect()
    for r in got:
        assert r["b"] == brute_spans(texts[r["doc_id"]])
        assert set(filter(None, r["b"].split(","))) <= set(r["s"].split(","))
    assert len(got) == len(texts) and personal_data.personal_data(df.filter("false"), ["doc_id"]).count() == 0


def test_addresses_with_parts_of_zero(spark):
    rng = random.Random(9)
    part = lambda: "".join(rng.choice("00125") for _ in range(rng.randint(1, 4)))
    fixed = ["10.0.0.1 127.0.0.1 192.168.10.0 0.0.0.0", "00.000.01.0 x 0.256.0.0 x 0256.0.0.1 x 0.0.0.00255", "0" * 4000 + ".0.0." + "0" * 4000, "0" * 4000 + ".0.0.256"]
    texts = fixed + [" ".join(".".join(part() for _ in range(4)) for _ in range(5)) for _ in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = personal_data.personal_data(df, ["doc_id"]).select("doc_id", personal_data.listed(F.filter("base", lambda m: m["kind"] == "ip")).alias("b")).collect()
    for r in got:
        assert r["b"] == ",".join(x for x in brute_spans(texts[r["doc_id"]]).split(",") if x.startswith("ip:"))
    assert len(got) == len(texts) and [r["b"].count("ip:") for r in sorted(got)[:4]] == [4, 2, 1, 0]


def brute_votes(kind, m, ahead, after):
    hit = lambda pattern, t: regex.search(pattern, t) is not None
    form, listed, context = hit(personal_data.STRICT[kind], m), hit(personal_data.GAZETTEER[kind], m), hit(personal_data.CONTEXT[kind], ahead)
    if kind == "secret":
        path = hit(r"[\p{L}\p{N}./?&#]$", ahead) or hit(r"^[.][\p{L}\p{N}]|^[?&/]", after)
        return (2 * form - 1, int(listed), int(context), -1 if path else int(hit(r"""[=:]\s?["']?$""", ahead)))
    return (2 * form - 1, 2 * listed - 1, int(context), -1 if hit(r"[\p{L}\p{N}_=/#$]$", ahead) or hit(r"^[\p{L}\p{N}_=/]", after) else 0)


def brute_shape(m):
    n = len(m)
    return (sum(n >= x for x in (8, 16, 32, 64)), sum(c in "0123456789" for c in m) * 5 // n, min(8, len(set(m)) // 4), int(any(c.islower() for c in m)) + 2 * int(any(c.isupper() for c in m)))


def test_added_spans_against_a_plain_version(spark):
    """Candidates, votes, shapes and verdicts of all loose kinds, computed one span at a time."""
    rng = random.Random(21)
    key = lambda n, of: "".join(rng.choice(of) for _ in range(n))
    makers = [
        lambda: f'token = "{key(40, "0123456789abcdef")}"',
        lambda: f"api_key: {key(32, 'ABCDEFGHabcdefgh0123456789')}",
        lambda: f"see /archive/{key(24, 'abcdefgh-')}9.html",
        lambda: f"AKIA{key(16, 'ABCDEFGHJK234567')}",
        lambda: f"call ({rng.randint(201, 989)}) 555-{rng.randint(1000, 9999)}",
        lambda: f"+1 ({rng.randint(201, 989)}) 555-{rng.randint(1000, 9999)}",
        lambda: f"mail {rng.choice(['ann.lee', 'x' * 80])} [at] {rng.choice(['mail', 'list'])} [dot] {rng.choice(['org', 'zzz', 'de'])}",
        lambda: f"a{rng.randint(0, 9)}@b.com (at) c.org",
        lambda: f"from Dr. {rng.choice(['Anna', 'Peter', 'Zorp'])} {rng.choice(['Miller', 'X'])}",
        lambda: f"IBAN {rng.choice(['DE', 'FR', 'XX'])}{key(2, '0123456789')} {key(4, '0123456789')} {key(4, '0123456789')} {key(4, '0123456789')} {key(4, '0123456789')} {key(2, '0123456789')}",
        lambda: key(30, "abcdefgh") + str(rng.randint(0, 9)),
    ]
    texts = [" ".join(rng.choice([rng.choice(makers)(), rng.choice(WORDS), "é😀"]) for _ in range(rng.randint(1, 12))) for _ in range(200)] + [None, "", " ".join(makers[0]() for _ in range(400)), "token = " + key(5000, "0123456789abcdef")]
    texts += texts[:5]
    found, counts = [], collections.Counter()
    for t in texts:
        own = []
        for kind, pattern in personal_data.LOOSE.items():
            for m in regex.finditer(pattern, t or ""):
                # What stands ahead starts at the end of the match before.
                last = max((x.end() for x in regex.finditer(pattern, t) if x.end() <= m.start()), default=0)
                ahead, after = t[max(last, m.start() - personal_data.AROUND) : m.start()], t[m.end() : m.end() + 2]
                if kind == "email" and (ahead.endswith("@") or after.startswith("@")) or kind == "phone" and regex.search(r"\+[0-9][ ().0-9-]*$", ahead):
                    continue
                own.append((kind, m.start(), m.end(), (kind, brute_votes(kind, m[0], ahead, after), brute_shape(m[0]))))
                counts[own[-1][3]] += 1
        found.append(own)
    weights = personal_data.train(dict(counts))
    expected = []
    for t, own in zip(texts, found, strict=True):
        yes = [f"{k}:{a}:{b}" for k, a, b, what in own if sum(weights[x] for x in personal_data.features(*what)) > np.log(personal_data.THRESHOLD / (1 - personal_data.THRESHOLD))]
        every = [*filter(None, brute_spans(t).split(",")), *yes]
        expected.append(",".join(sorted(every, key=lambda x: (personal_data.KINDS.index(x.split(":")[0]), *map(int, x.split(":")[1:])))))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = personal_data.personal_data(df, ["doc_id"]).select("doc_id", personal_data.listed(F.col("spans")).alias("s")).collect()
    assert [r["s"] for r in sorted(got)] == expected
    kinds = {x.split(":")[0] for e in expected for x in e.split(",") if x}
    assert {"secret", "phone", "email"} <= kinds


CLASHES = ["size", "source_size", "target", "copies", "taken", "n_words", "_host", "hits", "items", "base", "spans", "host", "path", "rule", "node", "key", "prefix", "n_shingles", "group", "lines", "shard", "text_crc32", "n_bytes", "removed", "kept", "own_text", "thread", "depth", "root", "n_linked", "main_text", "__x", "__t"]


def test_columns_of_any_name_pass_through(spark, docs, rows):
    """Every operator with kept columns named like its results and inner columns: no crash, nothing dropped, and the same results."""
    named = docs.filter("doc_id IS NOT NULL").withColumns({c: F.concat(F.lit(c + ":"), F.col("doc_id")) for c in CLASHES})
    items = spark.createDataFrame([(0, rows[3][1])], "item_id long, text string")
    keep = ["doc_id", *CLASHES]
    pages = named.withColumns({"url": F.lit("http://a.net/x"), "html": F.lit("<p>one two</p>")})
    runs = {
        "sizes": lambda d, k: mixing.with_sizes(d, keep=tuple([*k, "source"])),
        "rules": lambda d, k: line_rules.judged(d, k),
        "benchmark": lambda d, k: decontaminate.contaminated_words(d, items, k),
        "spans": lambda d, k: personal_data.personal_data(d, k),
        "urls": lambda d, k: url_filter.judge_urls(pages if len(k) > 1 else pages.drop(*CLASHES), tuple(k)),
        "html": lambda d, k: html_text.extract(pages if len(k) > 1 else pages.drop(*CLASHES), tuple(k)),
        "groups": lambda d, k: jaccard_join.similar_groups(d, k),
        "repeats": lambda d, k: suffix_dedup.without_repeats(d, k),
        "shards": lambda d, k: kd_sharding.kd_shards(d, 2, keep=tuple(k))[0],
        "sharded": lambda d, k: kd_sharding.with_shard(d, kd_sharding.kd_shards(d, 2, keep=tuple(k))[1]),
        "mix": lambda d, k: mixing.pareto_mix(mixing.with_sizes(d, keep=tuple([*k, "source"]))),
        "quotes": lambda d, k: quotations.linked(d.withColumns({"conv_id": F.lit(1).cast("bigint"), "turn": F.col("doc_id")})),
    }
    for name, run in runs.items():
        plain, found = run(named.drop(*CLASHES), ["doc_id"]), run(named, keep)
        results = [c for c in plain.columns if c != "doc_id"]
        assert set(plain.columns) <= set(found.columns), name
        both = [sorted(map(repr, df.select("doc_id", *results).collect())) for df in (found, plain)]
        assert both[0] == both[1], name
        for c in CLASHES if name not in ("mix", "quotes") else [x for x in CLASHES if not x.startswith("__")]:
            back = next(x for x in (c, c + "_in", c + "_in_in") if x in found.columns and x not in results)
            assert all(r[0] == f"{c}:{r[1]}" for r in found.select(f"`{back}`", "doc_id").collect()), (name, c)


def test_reliabilities_find_the_better_labeler():
    counts = {("name", (1, 1, 1, 0)): 80, ("name", (1, 1, 0, 0)): 60, ("name", (-1, -1, 0, -1)): 90, ("name", (-1, -1, 1, 0)): 40, ("name", (1, -1, 0, -1)): 5}
    odds, likely = personal_data.reliabilities(counts)
    assert likely["name", (1, 1, 1, 0)] > 0.9 > 0.1 > likely["name", (-1, -1, 0, -1)]
    assert odds["true"][0][1] > odds["false"][0][1]


def plain_shards(rows, depth):
    """doc_id to shard by sorting the rows of every node: weighted median of the widest measure, ties by checksum, then id."""
    wide = {c: max(1, max(r[c] for r in rows) - min(r[c] for r in rows)) for c in kd_sharding.DIMENSIONS}

    def divide(rows, at, level):
        if level == depth or not rows:
            return {r["doc_id"]: at for r in rows}
        total = sum(r["size"] for r in rows)
        spread = lambda c: (max(r[c] for r in rows) - min(r[c] for r in rows)) / wide[c]
        column = max(kd_sharding.DIMENSIONS, key=lambda c: (spread(c), -kd_sharding.DIMENSIONS.index(c)))
        goal, here, names, values, ahead = total / 2, rows, [], [], 0
        while True:
            before = 0
            for v in sorted({r[column] for r in here}):
                own = sum(r["size"] for r in here if r[column] == v)
                if before + own >= goal - ahead or v == max(r[column] for r in here):
                    break
                before += own
            lower, upper = ahead + before, ahead + before + own
            names.append(column)
            rest = [c for c in kd_sharding.TIES if c not in names]
            if min(goal - lower, upper - goal) > kd_sharding.TOLERANCE * total and rest:
                values.append(v)
                here, ahead, column = [r for r in here if r[column] == v], lower, rest[0]
                continue
            values.append(v if upper - goal <= goal - lower else v - 1)
            break
        above = lambda r: tuple(r[c] for c in names) > tuple(values)
        low, high = [r for r in rows if not above(r)], [r for r in rows if above(r)]
        return divide(low, 2 * at, level + 1) | divide(high, 2 * at + 1, level + 1)

    return {k: v - 2**depth for k, v in divide(rows, 1, 0).items()}


@pytest.mark.parametrize("depth", [1, 3, 4])
def test_kd_shards_against_sorting(spark, depth):
    rng = random.Random(depth)
    copy = "same " * 40
    rows = [(i, copy if i % 5 == 0 else "\n".join(" ".join(rng.choice(["word", "é", "12", "x" * rng.randint(1, 30)]) for _ in range(rng.randint(0, 30))) for _ in range(rng.randint(1, 4)))) for i in range(300)] + [(300, None), (301, "")]
    held, _ = kd_sharding.kd_shards(spark.createDataFrame(rows, "doc_id long, text string"), 2**depth)
    measured = []
    for i, t in rows:
        t = t or ""
        n = len(t.encode())
        measured.append({"doc_id": i, "size": n + 1, "text_crc32": zlib.crc32(t.encode()), "beyond_ascii": n - len(t), "lines": t.count("\n") + 1, "spaces": t.count(" "), "digits": sum(c in "0123456789" for c in t)})
    assert {r["doc_id"]: r["shard"] for r in held.collect()} == plain_shards(measured, depth)


def test_kd_shards(docs, rows, empty):
    held, tree = kd_sharding.kd_shards(docs, 4)
    got = kd_sharding.with_slots(held).collect()
    assert len(got) == len(rows)
    size = collections.Counter()
    for r in got:
        size[r["shard"]] += r["size"]
    biggest = max(r["size"] for r in got)
    assert max(size.values()) - min(size[k] for k in range(4)) <= 2 * biggest
    for k in range(4):
        assert sorted(r["slot"] for r in got if r["shard"] == k) == list(range(sum(r["shard"] == k for r in got)))
    texts = {r[0]: r[1] for r in rows}
    assert all(r["text_crc32"] == zlib.crc32((texts[r["doc_id"]] or "").encode()) for r in got)
    assert kd_sharding.with_shard(docs, tree).count() == len(rows)
    assert kd_sharding.kd_shards(empty, 4)[0].count() == 0


def test_kd_shards_split_a_heavy_group(spark):
    df = spark.range(800).selectExpr("id AS doc_id", "IF(id < 500, 'same text for all of these', concat('t', id, repeat('x', 20))) AS text")
    held, _ = kd_sharding.kd_shards(df, 8)
    sizes = [r["b"] for r in held.groupBy("shard").agg(F.sum("size").alias("b")).collect()]
    assert len(sizes) == 8 and max(sizes) < 1.1 * min(sizes)


def brute_rules(rows):
    lines = lambda t: [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    out = {}
    for r in rows:
        w, t = words(r[1]), r[1] or ""
        seen = collections.Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        hit = {p for i in range(len(w) - 7) if seen[tuple(w[i : i + 8])] > 1 for p in range(i, i + 8)}
        out[r[0]] = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines(t)) - len(set(lines(t))), len(hit), len(w) < 20 or 100 * len(hit) > 30 * len(w))
    return out


def test_line_rules(spark, docs, rows, empty):
    expected = brute_rules(rows)
    for r in line_rules.judged(docs.withColumn("kept", F.lit("clash")), ["doc_id"]).collect():
        assert tuple(r[c] for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")) == expected[r["doc_id"]]
    assert line_rules.judged(empty, ["doc_id"]).count() == 0
    own = lambda i: " ".join("abcdefghij"[i // 10] + "klmnopqrst"[i % 10] + WORDS[j % 20] for j in range(25))
    made = [(i, "Cookie  Policy 12\n" + own(i), "h") for i in range(60)] + [(100 + i, "cookie policy 7 and much more of the same old notice for all\n" * 1 + "a b", "h") for i in range(40)]
    got = line_rules.judged(spark.createDataFrame(made, "doc_id long, text string, source string"), ["doc_id"], with_text=True).collect()
    for r in got:
        if r["doc_id"] < 60:
            assert r["kept"] and r["removed"] == 3 and r["clean_text"] == own(r["doc_id"])


def brute_windows(rows, items, width=10):
    tok = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
    wins = collections.defaultdict(set)
    for k, t in items:
        w = tok(t)
        for i in range(max(0, len(w) - min(width, len(w)) + 1) if w else 0):
            wins[tuple(w[i : i + min(width, len(w))])].add(str(k))
    out = {}
    for r in rows:
        w = tok(r[1])
        hit, found = set(), set()
        for size in {len(x) for x in wins}:
            for i in range(len(w) - size + 1):
                if tuple(w[i : i + size]) in wins:
                    hit |= set(range(i, i + size))
                    found |= wins[tuple(w[i : i + size])]
        out[r[0]] = (len(w), len(hit), sorted(found))
    return out


def test_decontamination(spark, docs, rows, empty, monkeypatch):
    items = [(0, " ".join(words(rows[3][1])[5:25])), (1, "alpha1"), (2, None), (3, ""), (7, rows[8][1].upper()), (10, "no such words anywhere at all")]
    df = spark.createDataFrame(items, "item_id long, text string")
    expected = brute_windows(rows, items)
    for block in (decontaminate.BLOCK_BYTES, 200):
        monkeypatch.setattr(decontaminate, "BLOCK_BYTES", block)
        for r in decontaminate.contaminated_words(docs, df, ["doc_id"]).collect():
            assert (r["n_words"], sum(s["stop"] - s["start"] for s in r["hits"]), r["items"]) == expected[r["doc_id"]]
    assert decontaminate.contaminated_words(empty, df, ["doc_id"]).count() == 0
    assert all(not r["hits"] for r in decontaminate.contaminated_words(docs, df.filter("false"), ["doc_id"]).collect())


def brute_components(rows, width, percent):
    sets = {}
    for k, r in enumerate(rows):
        w = words("".join(c.lower() if "A" <= c <= "Z" else c for c in r[1] or ""))
        sets[k] = frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) or (frozenset([tuple(w)]) if w else frozenset())
    label = dict.fromkeys(sets)
    for k in sets:
        label[k] = k
    for a in sets:
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = label[a], label[b]
                label = {k: min(x, y) if v in (x, y) else v for k, v in label.items()}
    return sets, label


def same_groups(found, rows, width, percent):
    sets, label = brute_components(rows, width, percent)
    groups, expected = collections.defaultdict(set), collections.defaultdict(set)
    for r in found:
        if r["group"] is not None:
            groups[r["group"]].add(r["doc_id"])
    for k, v in label.items():
        if sets[k]:
            expected[v].add(rows[k][0])
    assert sorted(map(str, map(sorted, [[str(x) for x in g] for g in groups.values()]))) == sorted(map(str, map(sorted, [[str(x) for x in g] for g in expected.values()])))
    assert {r["doc_id"]: r["n_shingles"] for r in found} == {rows[k][0]: len(s) for k, s in sets.items()}


@pytest.mark.parametrize(("width", "percent", "tile_bytes"), [(4, 85, 8 << 20), (5, 80, 3000), (2, 50, 3000)])
def test_jaccard_join(docs, rows, empty, width, percent, tile_bytes):
    same_groups(jaccard_join.similar_groups(docs, ["doc_id"], width=width, percent=percent, tile_bytes=tile_bytes).collect(), rows, width, percent)
    assert jaccard_join.similar_groups(empty, ["doc_id"]).count() == 0


@pytest.mark.parametrize("tile_bytes", [8 << 20, 20_000, 4000])
def test_jaccard_join_of_a_large_group(spark, tile_bytes):
    """Variants of one text, at similarities around the limit, and chains of such: one tile, many tiles, pairs of tiles."""
    rng = random.Random(11)
    base = [rng.choice(WORDS) + str(rng.randint(0, 99)) for _ in range(120)]
    rows = [(0, " ".join(base))]
    for i in range(1, 120):
        w = list(base) if i % 3 else words(rows[-1][1])
        for _ in range(rng.randint(1, 5)):
            w[rng.randrange(len(w))] = f"new{rng.randint(0, 10**6)}"
        rows.append((i, " ".join(w)))
    found = jaccard_join.similar_groups(spark.createDataFrame(rows, "doc_id long, text string"), ["doc_id"], tile_bytes=tile_bytes).collect()
    same_groups(found, rows, 4, 85)


def test_one_of_each_group(spark, docs, rows):
    twice = docs.unionByName(docs.filter("doc_id = 3"))
    got = jaccard_join.one_of_each_group(twice, width=5, percent=80).collect()
    sets, label = brute_components(rows, 5, 80)
    best = {}
    for k, v in label.items():
        if sets[k]:
            best[v] = min((x for x in (best.get(v), rows[k][0]) if x is not None), default=None)
    expected = sorted(str(b) for b in best.values()) + [str(rows[k][0]) for k in sets if not sets[k]]
    assert sorted(str(r["doc_id"]) for r in got) == sorted(expected)


def test_components(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(0, 40)] + [(100, 101), (7, 7), (200, 100)], "a long, b long")
    got = {r["node"]: r["label"] for r in components(chain).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[200] == got[101] == 100
    assert components(chain.filter("false")).count() == 0


def test_url_filter(spark):
    urls = [(1, "http://a.example.net/en/1"), (2, "https://x.net/"), (3, "http://example.com/de/5?x"), (4, "http://m.example.org/fr/2"), (5, None), (6, "no scheme"), (7, "HTTP://WWW.Cheap-Pills.example.com/en/3"), (8, "http://therin.example.com/en/770#top"), (9, "http://notexample.com/de/"), (10, "http://x.net")]
    got = {r["page_id"]: r for r in url_filter.judge_urls(spark.createDataFrame(urls, "page_id long, url string")).collect()}
    assert (got[1]["rule"], got[1]["verdict"]) == ("example.net/en/", "allow") and (got[2]["rule"], got[2]["verdict"]) == ("net/", "block")
    assert got[3]["verdict"] == "block" and got[4]["verdict"] == "allow" and got[5]["host"] == "" and got[6]["path"] == ""
    assert got[7]["host"] == "www.cheap-pills.example.com" and got[7]["verdict"] == "block" and got[8]["verdict"] == "allow"
    assert got[9]["rule"] is None and got[10]["rule"] is None and got[10]["path"] == ""
    held_out = url_filter.labelled_urls(800, seed=123)
    p = url_filter.default_model().probability([u for u, _ in held_out])
    assert np.mean((p > 0.5) == np.array([b for _, b in held_out])) > 0.9


def test_sets_are_not_sent_for_every_shingle_in_common(spark, monkeypatch):
    """Near copies in one neighbourhood, which passages in common make too large for one tile."""
    rng = random.Random(12)
    made = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    link, rows = made(95), []
    for i in range(60):
        passage, link = link, made(95)
        base = made(10) + passage + made(10) + link  # the next pair has this passage, too
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(base[:-1]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sent, inner = [], jaccard_join.joined_tiles
    monkeypatch.setattr(jaccard_join, "joined_tiles", lambda tiles, percent: sent.append(tiles.count()) or inner(tiles, percent))
    got = jaccard_join.similar_groups(docs, ["doc_id"], tile_bytes=40_000).collect()
    groups = collections.defaultdict(set)
    for r in got:
        groups[r["group"]].add(r["doc_id"])
    assert sorted(sorted(g) for g in groups.values()) == [[2 * i, 2 * i + 1] for i in range(60)]
    assert len(sent) > 1 and sum(sent) <= 5 * len(rows)


def test_rows_of_use_keeps_what_may_be_linked(spark):
    sets = [list(range(0, 200)), list(range(5, 205)), list(range(1000, 1200)), list(range(1000, 1190)), list(range(150, 350))]
    hashed = [np.sort(jaccard_join.mix64(np.array(s, dtype=np.uint64))) for s in sets]
    row = lambda tile, k, group, half: (tile, k, len(sets[k]), group, half, jaccard_join._signature(hashed[k]))
    rows = [row(1, 0, 0, 0), row(1, 1, 1, 0), row(1, 4, 4, 0), row(2, 1, 1, 0), row(2, 0, 0, 0), row(3, 2, 9, 0), row(3, 3, 9, 0), row(4, 2, 2, 0), row(4, 3, 3, 1), row(5, 2, 2, 0), row(5, 3, 3, 0), row(5, 0, 0, 1), row(6, 4, 4, 0)]
    got = jaccard_join._rows_of_use(spark.createDataFrame(rows, "tile long, node long, n long, group long, half int, signature binary"), 85).collect()
    tiles = collections.defaultdict(list)
    for r in got:
        tiles[r["tile"]].append((r["node"], r["n"], r["group"], r["half"]))
    # The first two tiles are left with the same rows and become one; the third is of one group; in the fifth both are of one half.
    assert sorted(sorted(t) for t in tiles.values()) == [[(0, 200, 0, 0), (1, 200, 1, 0)], [(2, 200, 2, 0), (3, 190, 3, 1)]]
