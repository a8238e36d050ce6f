"""Personal data by weak supervision, in DataFrame expressions only.

Patterns propose spans. Labellers vote on every span for or against personal data, or
abstain: patterns with check rules, gazetteers of endings, prefixes and key names, and
words in the context. Votes are counted by pattern over the whole corpus, a table
whose size depends on the labellers alone; expectation-maximisation over it estimates
how reliable each labeller is for each kind, and its posteriors train a linear span
classifier. Spans of the fixed base kinds stay whatever the classifier says.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.io import cut

#: Span patterns. Possessive forms and look-behinds match the same texts in linear time.
BASE = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
    "secret": r"(?i)(?<![a-z0-9_])(?:api[_-]?key|access[_-]?key|auth[_-]?token|token|secret|password|passwd|pwd)\s?[=:]\s?[\"']?[A-Za-z0-9_/+=-]{6,}[\"']?",
    "local_phone": r"(?<![0-9+(])(?<!\+[0-9]{1,3} )(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9])",
    "national_id": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "spelled_email": r"(?i)(?<![a-z0-9])[a-z0-9._-]{1,64}(?: at | ?\[at\] ?| ?\(at\) ?)[a-z0-9-]{1,63}(?: dot | ?\[dot\] ?| ?\(dot\) ?)[a-z]{2,24}(?![a-z0-9])",
}
KINDS = tuple(PATTERNS)
#: Gazetteers and context words of the labellers.
ENDINGS = "com org net edu gov io info biz co uk us ca au de fr es it nl pl se no dk fi pt ch at be eu jp cn kr in br mx ru".split()
CONTEXT_FOR = "mail email e-mail contact write reach call phone tel telephone mobile fax cell card visa mastercard amex credit payment account ip host address server login from password token secret key credential ssn social".split()
CONTEXT_AGAINST = "version release build isbn issn doi order invoice figure section chapter page part serial model article sha commit example placeholder dummy sample".split()
VOTERS = ("rule", "gazetteer", "context", "against", "edges", "spread")
#: Characters of context on either side.
BEFORE, AFTER = 40, 12


#: Entries of a list that are summed at once, so that a long list costs little more than its length.
BLOCK = 64


def _total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0), lambda s, x: s + x)


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, "[^0-9]", "")


def _valid(kind: str, v: Column) -> Column:
    """The check rule that a match of ``kind`` must pass to be a span at all."""
    if kind == "ip":
        return F.forall(F.split(v, r"\."), lambda p: F.regexp_replace(p, "^0+", "").rlike(r"^(?:|[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"))
    if kind == "card":
        return F.length(_digits(v)).between(13, 19) & F.call_function("luhn_check", _digits(v))
    if kind == "phone":
        return F.length(_digits(v)).between(9, 15)
    return F.lit(True)


def _hint(kind: str, text: Column) -> Column:
    """A cheap test that every text with a match passes."""
    if kind == "email":
        return F.contains(text, F.lit("@"))
    if kind == "phone":
        return F.contains(text, F.lit("+"))
    if kind == "secret":
        return F.contains(text, F.lit("=")) | F.contains(text, F.lit(":"))
    if kind == "spelled_email":
        low = F.lower(text)
        return (F.contains(low, F.lit(" at ")) | F.contains(low, F.lit("at]")) | F.contains(low, F.lit("at)"))) & F.contains(low, F.lit("dot"))
    return text.rlike("[0-9]")


def _rule(kind: str, v: Column) -> Column:
    """1 or 0 by the form of the match alone."""
    d = _digits(v)
    varied = F.size(F.array_distinct(F.split(d, ""))) >= 4
    by = {
        "email": ~F.contains(v, F.lit("..")) & ~v.startswith(".") & (F.length(F.substring_index(v, "@", 1)) <= 64),
        "ip": ~v.rlike(r"^(?:0|127|22[4-9]|23[0-9]|24[0-9]|25[0-5])\.") & ~v.rlike(r"(?:^|\.)0[0-9]"),
        "card": varied & ~v.rlike("[ -]{2}"),
        "phone": varied & ~v.rlike(r"\.\."),
        "secret": v.rlike("[0-9]") & (F.length(v) >= 12),
        "local_phone": varied & v.rlike(r"^\(?[2-9]"),
        "national_id": ~v.rlike("^(?:000|666|9)") & ~v.rlike("-00-|-0000$"),
        "spelled_email": F.lower(v).rlike(r"\[at\]|\(at\)|\[dot\]|\(dot\)"),
    }[kind]
    return F.when(by, 1).otherwise(0)


def _gazetteer(kind: str, v: Column) -> Column:
    """1 or 0 by lists of endings, prefixes and key names; null where no list speaks."""
    ending = F.lower(F.regexp_extract(v, r"([A-Za-z]+)\W*$", 1))
    by = {
        "email": F.when(ending.isin(ENDINGS), 1).otherwise(0),
        "ip": F.when(v.rlike(r"^(?:10|192\.168|172\.(?:1[6-9]|2[0-9]|3[01]))\."), 0),
        "card": F.when(_digits(v).rlike("^(?:4|5[1-5]|2[2-7]|3[47]|6)"), 1).otherwise(0),
        "phone": F.when(v.rlike(r"^\+(?:1|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|7|8[1246]|9[0-58])"), 1),
        "secret": F.when(F.lower(v).rlike("^(?:password|passwd|pwd|token|secret|api)"), 1),
        "local_phone": F.lit(None).cast("int"),
        "national_id": F.lit(None).cast("int"),
        "spelled_email": F.when(ending.isin(ENDINGS), 1).otherwise(0),
    }[kind]
    return by


def _votes(kind: str) -> Column:
    """Array of (kind, a, b, votes) of the valid matches, in text order, from the staged columns of ``candidates``."""
    gaps, found, lens, heads = (F.col(f"{c}_{kind}") for c in "gmlh")

    def one(m: Column, i: Column) -> Column:
        before, after = F.get(gaps, i), F.get(gaps, i + 1)
        block = F.floor(i / BLOCK).cast("int")
        start = F.get(heads, block) + _total(F.slice(lens, block * BLOCK + 1, i % BLOCK)) + F.length(before)
        words = F.split(F.lower(F.right(before, F.lit(BEFORE))), "[^a-z-]+")
        tail = F.lower(F.left(after, F.lit(AFTER)))
        known = lambda ws: F.arrays_overlap(words, F.lit(ws).cast("array<string>"))
        open_edge = F.right(before, F.lit(1)).rlike("[A-Za-z0-9]") | F.left(after, F.lit(1)).rlike("[A-Za-z0-9]")
        votes = [
            _rule(kind, m),
            _gazetteer(kind, m),
            F.when(known(CONTEXT_FOR), 1),
            F.when(known(CONTEXT_AGAINST) | F.contains(tail, F.lit("version")), 0),
            F.when(open_edge, 0).otherwise(1),
            F.when(F.length(m) > 120, 0),
        ]
        code = F.concat(*[F.coalesce(v.cast("string"), F.lit("-")) for v in votes])
        return F.struct(F.lit(kind).alias("kind"), start.alias("a"), (start + F.length(m)).alias("b"), F.when(_valid(kind, m), code).alias("votes"))

    some = F.filter(F.transform(found, one), lambda s: s["votes"].isNotNull())
    none = F.array().cast("array<struct<kind:string,a:int,b:int,votes:string>>")
    return F.when(F.size(heads) > 0, some).otherwise(none)


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, c_<kind> ...)``: the valid matches of every kind in every row, with the labellers' votes."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return _staged(rows, F.col("text"), ["doc_id"])


def _staged(df: DataFrame, text: Column, carry: list[str]) -> DataFrame:
    """``carry`` with c_<kind> for every kind.

    Matches and the gaps between them come from one pattern each; a match stands where
    the lengths before it add up to. Each step is a projection of its own, since an
    expression written inside a lambda is worked out again for every element.
    """
    strings, ints = F.array().cast("array<string>"), F.array().cast("array<int>")
    df = df.select("*", *[(_hint(k, text) & text.rlike(PATTERNS[k])).alias(f"has_{k}") for k in KINDS])
    df = df.select(
        *carry,
        *[F.when(F.col(f"has_{k}"), F.split(text, PATTERNS[k], -1)).otherwise(strings).alias(f"g_{k}") for k in KINDS],
        *[F.when(F.col(f"has_{k}"), F.regexp_extract_all(text, F.lit(PATTERNS[k]), F.lit(0))).otherwise(strings).alias(f"m_{k}") for k in KINDS],
    )
    df = df.select("*", *[_lengths(k).alias(f"l_{k}") for k in KINDS])
    last = lambda k: F.floor((F.size(f"l_{k}") - 1) / BLOCK).cast("int")
    df = df.select("*", *[F.when(F.size(f"l_{k}") > 0, _sums(F.sequence(F.lit(0), last(k)), F.col(f"l_{k}"))).otherwise(ints).alias(f"b_{k}") for k in KINDS])
    df = df.select("*", *[_before(F.col(f"b_{k}")).alias(f"h_{k}") for k in KINDS])
    return df.select(*carry, *[_votes(k).alias(f"c_{k}") for k in KINDS])


def _lengths(kind: str) -> Column:
    gaps = F.col(f"g_{kind}")
    return F.transform(f"m_{kind}", lambda m, i: F.length(F.get(gaps, i)) + F.length(m))


def _sums(blocks: Column, lens: Column) -> Column:
    return F.transform(blocks, lambda b: _total(F.slice(lens, b * BLOCK + 1, F.lit(BLOCK))))


def _before(sums: Column) -> Column:
    return F.transform(sums, lambda _, b: _total(F.slice(sums, F.lit(1), b)))


def vote_counts(found: DataFrame) -> dict[tuple[str, str], int]:
    """How often each pattern of votes came, by kind: at most kinds times 3 to the number of labellers rows."""
    spans = found.select(F.explode(F.concat(*[f"c_{k}" for k in KINDS])).alias("s"))
    return {(r["kind"], r["votes"]): r["n"] for r in spans.groupBy("s.kind", "s.votes").agg(F.count("*").alias("n")).collect()}


def posteriors(counts: dict[tuple[str, str], int], rounds: int = 50) -> tuple[dict, dict]:
    """Expectation-maximisation over counted vote patterns.

    Gives the posterior of each (kind, votes) and the reliability of each labeller:
    the chances that it votes yes on a personal and on another span, among its votes.
    """
    prior = dict.fromkeys(KINDS, 0.7)
    yes = {(v, c): 0.8 if c else 0.3 for v in range(len(VOTERS)) for c in (0, 1)}
    post: dict = {}
    for _ in range(rounds):
        for kind, votes in counts:
            like = [1 - prior[kind], prior[kind]]
            for v, x in enumerate(votes):
                if x != "-":
                    for c in (0, 1):
                        like[c] *= yes[v, c] if x == "1" else 1 - yes[v, c]
            post[kind, votes] = like[1] / (like[0] + like[1])
        for kind in KINDS:
            of = [(p, counts[k]) for k, p in post.items() if k[0] == kind]
            prior[kind] = min(0.98, (7 + sum(p * n for p, n in of)) / (10 + sum(n for _, n in of)))
        for v in range(len(VOTERS)):
            for c in (0, 1):
                w = [(votes[v], n * (post[kind, votes] if c else 1 - post[kind, votes])) for (kind, votes), n in counts.items() if votes[v] != "-"]
                lean = 16 if c else 6
                yes[v, c] = min(0.98, max(0.02, (lean + sum(n for x, n in w if x == "1")) / (20 + sum(n for _, n in w))))
        for v in range(len(VOTERS)):  # a labeller that would say yes rather to other spans is taken as silent
            if yes[v, 1] < yes[v, 0]:
                yes[v, 0] = yes[v, 1]
    return post, yes


def train(counts: dict[tuple[str, str], int], post: dict, rounds: int = 300, rate: float = 0.5) -> dict[str, float]:
    """Weights of the linear span classifier, fitted to the posteriors of the counted patterns."""
    rows = [([f"kind={k}", *[f"{VOTERS[i]}={x}" for i, x in enumerate(votes) if x != "-"]], post[k, votes], math.sqrt(n)) for (k, votes), n in sorted(counts.items())]
    weights = {f: 0.0 for names, _, _ in rows for f in names}
    total = sum(n for _, _, n in rows) or 1.0
    for _ in range(rounds):
        grad = dict.fromkeys(weights, 0.0)
        for names, y, n in rows:
            p = 1 / (1 + math.exp(-max(-30.0, min(30.0, sum(weights[f] for f in names)))))
            for f in names:
                grad[f] += n * (p - y)
        for f in weights:
            weights[f] -= rate * (grad[f] / total * 10 + 1e-3 * weights[f])
    return weights


def _personal(s: Column, weights: dict[str, float]) -> Column:
    score = F.lit(0.0)
    for kind in KINDS:
        score = score + F.when(s["kind"] == kind, weights.get(f"kind={kind}", 0.0)).otherwise(0.0)
    for i, name in enumerate(VOTERS):
        vote = F.substring(s["votes"], i + 1, 1)
        score = score + F.when(vote == "1", weights.get(f"{name}=1", 0.0)).when(vote == "0", weights.get(f"{name}=0", 0.0)).otherwise(0.0)
    return score >= 0


def find(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, base, spans)``: arrays of (kind, a, b) in code points, end exclusive, by kind and start.

    ``base`` holds every span of the base kinds, ``spans`` these and the ones of
    other kinds that the classifier accepts. A null text counts as empty. Repeated
    rows and null ids are kept; an empty table gives none.
    """
    found = cut(candidates(docs, id_col, text_col))
    counts = vote_counts(found)
    base, spans = _decided(train(counts, posteriors(counts)[0]))
    return found.select("doc_id", base.alias("base"), spans.alias("spans"), *[F.size(f"c_{k}").cast("long").alias(f"n_{k}") for k in BASE])


def _decided(weights: dict[str, float]) -> tuple[Column, Column]:
    """Base spans, and these with the spans of other kinds that the classifier accepts."""
    plain = lambda c: F.transform(c, lambda s: F.struct(s["kind"].alias("kind"), s["a"].alias("a"), s["b"].alias("b")))
    base = F.concat(*[plain(F.col(f"c_{k}")) for k in BASE])
    more = [plain(F.filter(f"c_{k}", lambda s: _personal(s, weights))) for k in KINDS if k not in BASE]
    return base, F.concat(base, *more)


def redact_documents(docs: DataFrame, text_col: str = "text", length_col: str = "n_chars") -> DataFrame:
    """``docs`` with the spans of every text replaced by their kinds, and ``length_col`` (if there) brought up to date.

    One pass over the texts learns the classifier, a second one redacts; rows are
    neither moved nor joined. Null texts stay null, and other columns stay as they are.
    """
    counts = vote_counts(candidates(docs.withColumn("doc_id", F.lit(0)), "doc_id", text_col))
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    whole = F.coalesce(F.col("row")[text_col].cast("string"), F.lit(""))
    spans = _decided(train(counts, posteriors(counts)[0]))[1]
    found = _staged(packed, whole, ["row"]).select("row", spans.alias("spans"))
    done = found.select("row", F.when(F.col("row")[text_col].isNotNull(), redact(F.col("row")[text_col], F.col("spans"))).alias("new"))
    new = {text_col: F.col("new"), length_col: F.length("new").cast("long")}
    return done.select(*[(new[c] if c in new else F.col("row")[c]).alias(c) for c in docs.columns])


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["a"].cast("string"), s["b"].cast("string"))), ",")


def digests(found: DataFrame) -> DataFrame:
    """Counts, digest of the base spans and the list of all spans from ``find``."""
    return found.select("doc_id", *[f"n_{k}" for k in BASE], F.sha2(_listed(F.col("base")).cast("binary"), 256).alias("base_sha256"), _listed(F.col("spans")).alias("spans"))


def redact(text: Column, spans: Column) -> Column:
    """``text`` with every span replaced by its kind in angle brackets; where spans overlap, the first to start stands."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        gap = F.substring(text, acc["at"] + 1, s["a"] - acc["at"])
        more = F.struct(s["b"].alias("at"), F.concat(acc["out"], F.array(gap, F.concat(F.lit("<"), s["kind"], F.lit(">")))).alias("out"))
        return F.when(s["a"] >= acc["at"], more).otherwise(acc)

    done = lambda acc: F.concat(F.array_join(acc["out"], ""), F.substring(text, acc["at"] + 1, F.length(text)))
    by_start = F.array_sort(F.transform(spans, lambda s: F.struct(s["a"].alias("a"), s["b"].alias("b"), s["kind"].alias("kind"))))
    return F.when(F.size(spans) > 0, F.aggregate(by_start, start, step, done)).otherwise(text)
