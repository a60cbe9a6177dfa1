"""Personal data by weak supervision. Built-in column functions only.

Patterns give candidate spans; labelers vote on each: the strict form of its kind, a
gazetteer (mail domains, given names, account lengths by country, prefixes of issued keys), cue
words in the context before it, and the characters around it. How often each pattern of votes
occurs for each kind is counted over all documents; expectation-maximisation on those counts
estimates how reliable each labeler is and how likely each pattern is a true span. A logistic
span classifier is trained on these probabilities, from the votes and from the shape of the span
itself (length, share of digits, different characters, upper and lower case), each by kind. Its weights
go back into the plan as literals. What comes to the driver is one row for each (kind, votes,
shape): a number of rows that kinds and buckets bound.

Spans with an exact definition (``BASE``) are always kept; the classifier decides on the others.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, keeping, table

KINDS = ("email", "ip", "card", "phone", "name", "iban", "secret")

# Definitions of the exact kinds, written so that each scan is linear in the text.
# A possessive run that may only start where a run starts finds what the plain pattern finds.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][ -])[0-9](?:[ -]?[0-9]){15,18}(?![0-9])(?![ -][0-9])",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
#: Cheap conditions without which a text has no such span.
LIKELY = {"email": r"@[A-Za-z0-9-]", "ip": r"[0-9]\.[0-9]++\.[0-9]", "card": r"[0-9](?:[ -]?[0-9]){15}", "phone": r"\+[0-9]"}
#: A number up to 255. The zeros ahead give back one where the part is nothing but zeros.
PART = r"0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])"

# Looser forms that the labelers vote on; runs are possessive and start where a run starts, of any length.
LOOSE = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++ ?(?:\[at\]|\(at\)) ?[A-Za-z0-9-]++(?: ?(?:\[dot\]|\(dot\)|\.) ?[A-Za-z0-9-]++)++",
    "phone": r"(?<![0-9A-Za-z+.-])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9-])",
    "name": r"\b(?:Mr|Mrs|Ms|Dr|Prof)\. \p{Lu}\p{L}++(?: \p{Lu}\p{L}++)?",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "secret": r"(?<![A-Za-z0-9_+/-])(?=[A-Za-z_+/-]*+[0-9])(?=[0-9_+/-]*+[A-Za-z])[A-Za-z0-9_+/-]{20,}+=*+",
}
LOOSE_LIKELY = {"email": r"[\[(]at[\])]", "phone": r"[0-9]{3}[ .-][0-9]{4}", "name": r"(?:Mr|Mrs|Ms|Dr|Prof)\. ", "iban": r"[A-Z]{2}[0-9]{2} ?[A-Z0-9]{4}", "secret": r"(?<![A-Za-z0-9_+/-])[A-Za-z0-9_+/-]{20}"}
# Word lists. Given names that are frequent in several languages; endings of mail domains; prefixes that issuers give to keys.
GIVEN_NAMES = """Adam Alain Albert Alex Alexander Alice Amanda Amelie Ana Andrea Andreas Andrew Angela Anna Anne Antonio Barbara Beatriz Ben Bernard Brian Camille Carlos Carmen Carol Caroline
Catherine Charles Charlotte Chloe Chris Christian Christine Claire Clara Claudia Daniel David Diego Dominique Donald Edward Elena Elisabeth Elizabeth Emily Emma Eric Eva Fernando Francisco Frank
Gabriel George Georg Gerard Hans Heinz Helen Helena Henri Henry Isabel Isabelle Jack Jacques James Jan Jane Javier Jean Jennifer Jessica Joan Johann John Jonas Jorge Jose Joseph Juan Julia Julie
Karen Karl Katharina Kevin Klaus Laura Lena Leon Linda Lisa Louis Louise Lucas Lucia Luis Luisa Manuel Marc Margaret Maria Marie Mark Marta Martin Mary Matthew Max Michael Michel Miguel Monica
Nancy Nathalie Nicolas Nina Olivia Oscar Pablo Patricia Paul Paula Pedro Peter Philippe Pierre Rachel Ramon Richard Robert Rosa Ruth Samuel Sandra Sarah Sebastian Sofia Sophie Stefan Stephen Susan
Susanne Sylvie Teresa Thomas Ursula Victor Walter William Wolfgang""".split()
DOMAIN_ENDINGS = "com org net edu gov mil int info biz io co ai app dev eu de fr es it pt nl be at ch lu ie uk us ca au nz mx ar br cl jp cn in kr ru pl cz se no fi dk gr tr za il".split()
KEY_PREFIXES = "AKIA ASIA AIza ghp_ gho_ ghs_ github_pat_ glpat- xoxb- xoxp- xoxa- sk_live_ rk_live_ pk_live_ sk- hf_ npm_ pypi- ya29 eyJ".split()
# Characters of an account number by country.
IBAN_LENGTHS = {"AT": 20, "BE": 16, "BG": 22, "CH": 21, "CY": 28, "CZ": 24, "DE": 22, "DK": 18, "EE": 20, "ES": 24, "FI": 18, "FR": 27, "GB": 22, "GR": 27, "HR": 21, "HU": 28, "IE": 22, "IS": 26, "IT": 27, "LI": 21, "LT": 20, "LU": 20, "LV": 21, "MC": 27, "MT": 31, "NL": 18, "NO": 15, "PL": 28, "PT": 25, "RO": 24, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "TR": 26}
#: Strict form, gazetteer and context by kind (regular expressions over the span and over what stands before it).
STRICT = {
    "email": r"^\S+ ?[\[(]at[\])] ?\S+$",
    "phone": r"^\(?[2-9][0-9]{2}\)?[ .-] ?[2-9][0-9]{2}[ .-][0-9]{4}$",
    "name": r"^(?:Mr|Mrs|Ms|Dr|Prof)\. \p{Lu}\p{Ll}+ \p{Lu}\p{Ll}+$",
    "iban": r"^[A-Z]{2}[0-9]{2}(?: ?[0-9]{4}){3}",
    "secret": r"^(?:[0-9a-f]{24,}|[0-9A-F]{24,}|(?=.*[a-z])(?=.*[A-Z])(?=.*[0-9].*[0-9].*[0-9])[A-Za-z0-9+/_-]{20,}=*)$",
}
GAZETTEER = {
    "email": rf"(?i)[.)\] ](?:{'|'.join(DOMAIN_ENDINGS)})$",
    "phone": r"^\(?[2-9][0-8][0-9]",  # area codes have no nine in the middle
    "name": rf"\. (?:{'|'.join(GIVEN_NAMES)})(?: |$)",
    "iban": "^(?:" + "|".join(f"(?=(?: ?[A-Z0-9]){{{n}}}$){c}" for c, n in IBAN_LENGTHS.items()) + ")",
    "secret": rf"^(?:{'|'.join(KEY_PREFIXES)})",
}
CONTEXT = {
    "email": r"(?i)\b(?:mail|e-mail|email|contact|write|reach)\b",
    "phone": r"(?i)\b(?:tel|telephone|phone|call|mobile|fax|ring)\b",
    "name": r"(?i)\b(?:by|from|with|dear|to|of|said|contact)\b",
    "iban": r"(?i)\b(?:iban|account|konto|compte|bank|transfer)\b",
    "secret": r"(?i)(?:token|secret|passw|pwd|api.?key|access.?key|private.?key|credential|bearer|authorization)[^.!?\n]{0,24}$",
}
LABELERS = ("form", "gazetteer", "context", "edges")
AROUND = 40
THRESHOLD = 0.9


def let(value: Column, use) -> Column:
    """``use(value)`` with the value computed once."""
    return F.transform(F.array(value), use)[0]


def running(sizes: Column) -> Column:
    """Sums of all elements before each element, by blocks of 64."""
    zero = F.lit(0).cast("bigint")
    total = lambda a: F.aggregate(a, zero, lambda s, x: s + x)
    count = lambda a: F.ceil(F.size(a) / 64).cast("int")

    def within(blocks: Column) -> Column:
        ahead = F.transform(blocks, lambda b, i: total(F.slice(blocks, 1, i)))
        return let(ahead, lambda p: F.transform(sizes, lambda x, i: p[F.floor(i / 64).cast("int")] + total(F.slice(sizes, (F.floor(i / 64) * 64).cast("int") + 1, F.pmod(i, F.lit(64))))))

    blocks = F.transform(F.sequence(F.lit(0), count(sizes) - 1), lambda b: total(F.slice(sizes, b * 64 + 1, 64)))
    return F.when(F.size(sizes) > 0, let(blocks, within)).otherwise(F.array().cast("array<bigint>"))


_FOUND = "array<struct<start:bigint,stop:bigint,span:string,ahead:string,after:string>>"


def occurrences(text: Column, pattern: str, likely: str) -> Column:
    """Leftmost matches that do not overlap: start, stop (code points), span, and what stands around."""

    def placed(hits: Column, gaps: Column) -> Column:
        sizes = F.transform(hits, lambda h, i: (F.length(h) + F.length(gaps[i])).cast("bigint"))
        row = lambda at: F.transform(hits, lambda h, i: F.struct((at[i] + F.length(gaps[i])).alias("start"), (at[i] + F.length(gaps[i]) + F.length(h)).alias("stop"), h.alias("span"), F.right(gaps[i], F.lit(AROUND)).alias("ahead"), F.left(gaps[i + 1], F.lit(2)).alias("after")))
        return let(sizes, lambda s: let(running(s), row))

    found = let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda hits: let(F.split(text, pattern, -1), lambda gaps: placed(hits, gaps)))
    return F.when(text.rlike(likely), found).otherwise(F.array().cast(_FOUND))


def _exact(kind: str, found: Column) -> Column:
    """Matches that pass the check of their kind."""
    digits = lambda m: F.regexp_replace(m["span"], "[^0-9]", "")
    checks = {
        "email": lambda m: F.lit(True),
        "ip": lambda m: m["span"].rlike(rf"^{PART}\.{PART}\.{PART}\.{PART}$"),
        "card": lambda m: F.expr("true") & F.call_function("luhn_check", digits(m)),
        "phone": lambda m: F.length(digits(m)).between(8, 15),
    }
    return F.filter(found, checks[kind])


def _fits(kind: str, found: Column) -> Column:
    """Candidates without those that lie in a span of ``BASE``, as far as the characters around them tell."""
    within = {"email": lambda m: m["ahead"].endswith("@") | m["after"].startswith("@"), "phone": lambda m: m["ahead"].rlike(r"\+[0-9][ ().0-9-]*$")}
    return F.filter(found, lambda m: ~within[kind](m)) if kind in within else found


def _votes(kind: str, m: Column) -> list[Column]:
    """1 for, -1 against, 0 no opinion."""
    yes_no = lambda c: F.when(c, 1).otherwise(-1)
    yes = lambda c: F.when(c, 1).otherwise(0)
    form, context = yes_no(m["span"].rlike(STRICT[kind])), yes(m["ahead"].rlike(CONTEXT[kind]))
    if kind == "secret":  # most keys have no prefix of an issuer; a value that is assigned or quoted speaks for one, a path against
        path = m["ahead"].rlike(r"[\p{L}\p{N}./?&#]$") | m["after"].rlike(r"^[.][\p{L}\p{N}]|^[?&/]")
        return [form, yes(m["span"].rlike(GAZETTEER[kind])), context, F.when(path, -1).when(m["ahead"].rlike(r"""[=:]\s?["']?$"""), 1).otherwise(0)]
    edges = m["ahead"].rlike(r"[\p{L}\p{N}_=/#$]$") | m["after"].rlike(r"^[\p{L}\p{N}_=/]")
    return [form, yes_no(m["span"].rlike(GAZETTEER[kind])), context, F.when(edges, -1).otherwise(0)]


SHAPES = ("length", "digits", "different", "cases")


def _shape(m: Column) -> list[Column]:
    """Buckets of the length (doubling from 8), of the share of digits (fifths), of different characters (by 4), and of upper and lower case."""
    n, digits = F.length(m["span"]), F.length(F.regexp_replace(m["span"], "[^0-9]", ""))
    different = F.size(F.array_distinct(F.split(m["span"], "")))
    double = F.when(n < 8, 0).when(n < 16, 1).when(n < 32, 2).when(n < 64, 3).otherwise(4)
    cases = F.when(m["span"].rlike(r"\p{Ll}"), 1).otherwise(0) + F.when(m["span"].rlike(r"\p{Lu}"), 2).otherwise(0)
    return [double, F.floor(digits * 5 / n).cast("int"), F.least(F.lit(8), F.floor(different / 4)).cast("int"), cases]


def find_spans(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep``, ``base`` and ``loose``: arrays of (kind, start, stop, span [, votes, shape])."""
    whole = F.coalesce(F.col(text), F.lit(""))
    df = docs.select(*keep, whole.alias("__t"))
    for kind, pattern in BASE.items():
        df = df.withColumn(f"__{kind}", _exact(kind, occurrences(F.col("__t"), pattern, LIKELY[kind])))
    for kind, pattern in LOOSE.items():
        df = df.withColumn(f"__loose_{kind}", _fits(kind, occurrences(F.col("__t"), pattern, LOOSE_LIKELY[kind])))

    def spans(kind: str, column: str, voted: bool) -> Column:
        more = lambda m: [F.array(*_votes(kind, m)).alias("votes"), F.array(*_shape(m)).alias("shape")] if voted else []
        return F.transform(column, lambda m: F.struct(F.lit(kind).alias("kind"), m["start"].alias("start"), m["stop"].alias("stop"), m["span"].alias("span"), *more(m)))

    base = F.concat(*[spans(k, f"__{k}", False) for k in BASE])
    loose = F.concat(*[spans(k, f"__loose_{k}", True) for k in LOOSE])
    return df.select(*keep, base.alias("base"), loose.alias("loose"))


def reliabilities(counts: dict[tuple, int], rounds: int = 60) -> tuple[dict[str, list[dict[int, float]]], dict[tuple, float]]:
    """Expectation-maximisation over (kind, votes) counts: for each true label and labeler the
    odds of each vote (shared by all kinds), a prior by kind, and the probability of each pattern."""
    votes = (-1, 0, 1)
    # Where there is no evidence, a labeler is right three times in four.
    prior = [[{v: 4.0 * (0.15 if v < 0 else 0.35 if v == 0 else 0.5) for v in votes} for _ in LABELERS], [{v: 4.0 * (0.5 if v < 0 else 0.35 if v == 0 else 0.15) for v in votes} for _ in LABELERS]]
    odds = [[{v: p[v] / sum(p.values()) for v in votes} for p in side] for side in prior]
    share = {k: 0.5 for k, _ in counts}
    likely: dict[tuple, float] = {}
    for _ in range(rounds):
        for (kind, pattern) in counts:
            scores = [math.log(s) + sum(math.log(odds[side][j][v]) for j, v in enumerate(pattern)) for side, s in ((0, share[kind]), (1, 1 - share[kind]))]
            likely[kind, pattern] = 1 / (1 + math.exp(min(500, scores[1] - scores[0])))
        for side in (0, 1):
            for j in range(len(LABELERS)):
                mass = dict(prior[side][j])
                for (kind, pattern), n in counts.items():
                    p = likely[kind, pattern]
                    mass[pattern[j]] += n * (p if side == 0 else 1 - p)
                odds[side][j] = {v: m / sum(mass.values()) for v, m in mass.items()}
        for k in share:
            n = sum(c for (kind, _), c in counts.items() if kind == k)
            yes = sum(c * likely[kind, pattern] for (kind, pattern), c in counts.items() if kind == k)
            share[k] = (yes + 1) / (n + 2)
    return {"true": odds[0], "false": odds[1]}, likely


def features(kind: str, votes: tuple, shape: tuple) -> list[str]:
    """Names of what the classifier sees of a span."""
    return [f"kind:{kind}", *(f"{kind}:{name}:{v}" for name, v in zip((*LABELERS, *SHAPES), (*votes, *shape), strict=True))]


def train(counts: dict[tuple, int], steps: int = 400, rate: float = 2.0, decay: float = 0.0005) -> dict[str, float]:
    """Weights of the logistic span classifier by feature, from (kind, votes, shape) counts; every kind counts alike."""
    by_votes: dict[tuple, int] = {}
    total: dict[str, int] = {}
    for (kind, votes, _), n in counts.items():
        by_votes[kind, votes] = by_votes.get((kind, votes), 0) + n
        total[kind] = total.get(kind, 0) + n
    _, likely = reliabilities(by_votes)
    rows = sorted(counts)
    names = [features(*r) for r in rows]
    number = {x: i for i, x in enumerate(sorted({x for r in names for x in r}))}
    seen = np.array([[number[x] for x in r] for r in names], dtype=np.int64).reshape(len(rows), 1 + len(LABELERS) + len(SHAPES))
    share, target = np.array([counts[r] / total[r[0]] for r in rows]), np.array([likely[r[0], r[1]] for r in rows])
    weights = np.zeros(len(number))
    for _ in range(steps):
        miss = share * (target - 1 / (1 + np.exp(-np.clip(weights[seen].sum(axis=1), -500, 500))))
        weights = weights * (1 - rate * decay) + rate * np.bincount(seen.ravel(), np.repeat(miss, seen.shape[1]), len(number))
    return {x: float(weights[i]) for x, i in number.items()}


def classified(found: DataFrame, keep: list[str], threshold: float = THRESHOLD) -> DataFrame:
    """``keep``, base, and spans: base and accepted loose ones, by kind as in KINDS, then start."""
    each = found.select(F.explode("loose").alias("m")).groupBy("m.kind", "m.votes", "m.shape").count()
    weights = train({(r["kind"], tuple(r["votes"]), tuple(r["shape"])): r["count"] for r in each.collect()})
    lookup = F.create_map(*[x for k, w in sorted({**{"none": 0.0}, **weights}.items()) for x in (F.lit(k), F.lit(float(w)))])
    weight = lambda name: F.coalesce(F.try_element_at(lookup, name), F.lit(0.0))
    bar = math.log(threshold / (1 - threshold))

    def accepted(m: Column) -> Column:
        z = weight(F.concat(F.lit("kind:"), m["kind"]))
        for names, values in ((LABELERS, m["votes"]), (SHAPES, m["shape"])):
            for j, name in enumerate(names):
                z = z + weight(F.concat(m["kind"], F.lit(f":{name}:"), values[j].cast("string")))
        return z > bar

    plain = lambda m: F.struct(F.array_position(F.lit(list(KINDS)), m["kind"]).alias("k"), m["start"].alias("start"), m["stop"].alias("stop"), m["kind"].alias("kind"), m["span"].alias("span"))
    spans = F.array_sort(F.concat(F.transform("base", plain), F.transform(F.filter("loose", accepted), plain)))
    return found.select(*keep, F.array_sort(F.transform("base", plain)).alias("base"), spans.alias("spans"))


@keeping
def personal_data(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep``, base and spans: arrays of (k, start, stop, kind, span), offsets in code points.

    A null text is empty and has no spans; a text is searched whole however long it is;
    repeated rows are treated alike; an empty table gives no rows.
    A kept column that has the name of a result comes back with ``_in`` added.
    """
    return classified(cut(find_spans(docs, keep, text)), keep)


def listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda m: F.concat_ws(":", m["kind"], m["start"].cast("string"), m["stop"].cast("string"))), ",")


def op5_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts and digests of the personal data of every document."""
    found = personal_data(table(spark, sf_dir, "documents"), ["doc_id"])
    count = lambda kind: F.size(F.filter("base", lambda m: m["kind"] == kind)).cast("bigint").alias(f"n_{kind}")
    return found.select("doc_id", *[count(k) for k in BASE], F.sha2(listed(F.col("base")), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"), F.size("spans").cast("bigint").alias("n_spans"))
