"""Downstream proxy: a word-bigram model of a corpus, put to five kinds of multiple choice.

It stands in for pretraining: it orders corpora by how much usable text they hold and
reproduces no number of a language model. A task row is either a candidate of a question,
with the bigram that joins it to what stands before it, or a bigram of a text that
candidates name by its key; candidate 0 is the right one.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_curation.functions.text import let, ngrams, portable_share, words
from spark_curation.io import stored

SMOOTH, VOCABULARY = 0.1, 100_000
#: Kinds of tasks by category, for category means.
CATEGORIES = {"continue": "reading", "order": "language", "reply": "commonsense", "continue_en": "language", "continue_de": "language", "continue_fr": "language", "continue_es": "language", "rank": "quality"}
#: Share of documents held out for continuation by language.
HELD_OUT = 0.1


def _bigrams(rows: DataFrame) -> DataFrame:
    """``(task, key, ws)`` to one row for each bigram of a text that candidates share."""
    g = rows.select("task", "key", F.explode(ngrams(F.col("ws"), 2)).alias("g"))
    return g.select("task", "key", F.lit(False).alias("asks"), F.lit(None).cast("long").alias("id"), F.lit(None).cast("int").alias("choice"), F.split("g", " ")[0].alias("w1"), F.split("g", " ")[1].alias("w2"))


def _asks(rows: DataFrame, w1: Column | None = None, w2: Column | None = None) -> DataFrame:
    """``(task, key, id, choice)``: one row for each candidate, with the bigram before its text if there is one."""
    none = F.lit(None).cast("string")
    return rows.select("task", "key", F.lit(True).alias("asks"), "id", "choice", (none if w1 is None else w1).alias("w1"), (none if w2 is None else w2).alias("w2"))


def _offer(rows: DataFrame, choices: int, buckets: int) -> DataFrame:
    """Candidates of ``(task, id, last, tail)``: a question's own tail and those of the next ones by id in its bucket, so no list of all is ever ordered.

    A tail is spelled once for all questions that it is offered to.
    """
    bucket = F.floor(portable_share(F.lit("bucket"), F.col("id").cast("string")) * buckets).cast("int")
    rows = rows.withColumn("b", bucket)
    w = Window.partitionBy("task", "b")
    ranked = rows.withColumns({"r": F.row_number().over(w.orderBy("id", "last", "tail")) - 1, "n": F.count("*").over(w)})
    ranked = stored(ranked)  # read three times, and its words are costly
    key = lambda r: F.concat_ws("|", F.col("b").cast("string"), F.col(r).cast("string"))
    asked = ranked.select("task", "b", "id", "last", F.explode(F.sequence(F.lit(0), F.lit(choices - 1))).alias("choice"), "r", "n").withColumn("from", F.pmod(F.col("r") + F.col("choice"), F.col("n")))
    got = asked.join(ranked.select("task", "b", F.col("r").alias("from"), F.col("tail")[0].alias("next")), ["task", "b", "from"])
    return _asks(got.withColumn("key", key("from")), F.col("last"), F.col("next")).unionByName(_bigrams(ranked.select("task", key("r").alias("key"), F.col("tail").alias("ws"))))


def continuation_tasks(items: DataFrame, task: Column | str = "continue", choices: int = 4, buckets: int = 4, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """The text's second half against those of other texts, after its first half's last word."""
    ws = words(F.lower(F.col(text_col)))
    named = F.lit(task) if isinstance(task, str) else task
    half = items.select(named.alias("task"), F.col(id_col).alias("id"), ws.alias("w")).where(F.size("w") >= 8).withColumn("m", (F.size("w") / 2).cast("int"))
    return _offer(half.select("task", "id", F.element_at("w", F.col("m")).alias("last"), F.slice("w", F.col("m") + 1, F.size("w")).alias("tail")), choices, buckets)


def language_tasks(docs: DataFrame, choices: int = 4, buckets: int = 4) -> DataFrame:
    """Continuation of held-out documents, each language a task of its own."""
    return continuation_tasks(docs.where(held_out(F.col("doc_id"))), F.concat(F.lit("continue_"), F.col("lang")), choices, buckets, "doc_id")


def held_out(doc_id: Column) -> Column:
    return portable_share(F.lit("held"), doc_id.cast("string")) < HELD_OUT


def order_tasks(items: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """A text as it is against its words in a shuffled order."""
    rows = items.select(F.col(id_col).alias("id"), words(F.lower(F.col(text_col))).alias("w")).where(F.size("w") >= 8)
    keyed = F.array_sort(F.transform("w", lambda x, i: F.struct(F.md5(F.concat(i.cast("string"), F.lit("|"), x)).alias("k"), x.alias("x"))))
    both = F.array(F.col("w"), F.transform(keyed, lambda p: p["x"]))
    each = rows.select(F.lit("order").alias("task"), "id", F.posexplode(both).alias("choice", "ws")).withColumn("key", F.concat_ws("|", F.col("id").cast("string"), F.col("choice").cast("string"), F.md5(F.array_join("ws", " "))))
    return _asks(each).unionByName(_bigrams(each.dropDuplicates(["key"])))


def reply_tasks(turns: DataFrame, choices: int = 4, buckets: int = 4) -> DataFrame:
    """The second turn of a conversation against those of others, after the first turn's last word."""
    first = turns.withColumn("k", F.row_number().over(Window.partitionBy("conv_id").orderBy("turn", "text"))).where("k <= 2")
    pair = first.groupBy("conv_id").agg(F.max(F.when(F.col("k") == 1, F.col("text"))).alias("a"), F.max(F.when(F.col("k") == 2, F.col("text"))).alias("b"))
    split = pair.select(F.lit("reply").alias("task"), F.col("conv_id").alias("id"), words(F.lower("a")).alias("a"), words(F.lower("b")).alias("tail")).where("size(a) > 0 and size(tail) > 0")
    return _offer(split.select("task", "id", F.element_at("a", -1).alias("last"), "tail"), choices, buckets)


def ranking_tasks(docs: DataFrame, labels: DataFrame, buckets: int = 4) -> DataFrame:
    """A good text against a bad one of the same language."""
    rows = docs.join(labels.select("doc_id", "quality"), "doc_id").select("doc_id", "lang", "quality", words(F.lower("text")).alias("ws")).where("size(ws) >= 2")
    rows = rows.withColumn("b", F.floor(portable_share(F.lit("bucket"), F.col("doc_id").cast("string")) * buckets).cast("int"))
    w = Window.partitionBy("lang", "b", "quality")
    ranked = rows.withColumns({"r": F.row_number().over(w.orderBy("doc_id", "ws")) - 1, "n": F.count("*").over(w)})
    ranked = ranked.withColumn("key", F.concat_ws("|", "lang", F.col("b").cast("string"), F.col("quality").cast("string"), F.col("r").cast("string")))
    ranked = stored(ranked)  # read four times
    good = ranked.where("quality = 1").select("lang", "b", F.col("r").alias("of"), F.col("key").alias("good"), F.col("n").alias("n_good"))
    n = good.groupBy("lang", "b").agg(F.max("n_good").alias("n_good"))
    bad = ranked.where("quality = 0").join(n, ["lang", "b"]).select("lang", "b", "doc_id", F.col("key").alias("bad"), F.pmod("r", F.col("n_good")).alias("of"))
    both = bad.join(good, ["lang", "b", "of"]).select(F.lit("rank").alias("task"), F.col("doc_id").alias("id"), F.posexplode(F.array("good", "bad")).alias("choice", "key"))
    spelled = ranked.select(F.lit("rank").alias("task"), "key", "ws").join(both.select("key").distinct(), "key", "left_semi")
    return _asks(both).unionByName(_bigrams(spelled))


def suite_tasks(benchmark: DataFrame, turns: DataFrame, docs: DataFrame, labels: DataFrame) -> DataFrame:
    """All five kinds."""
    parts = [continuation_tasks(benchmark), order_tasks(benchmark), reply_tasks(turns), language_tasks(docs), ranking_tasks(docs, labels)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def train(corpus: DataFrame, tasks: DataFrame | None = None, by: Sequence[str] = (), weight: Column | float = 1.0, text_col: str = "text") -> DataFrame:
    """``(by..., w1, w2, c2, c1)``: bigram and first-word counts, times how often a text is repeated to fill the budget.

    With ``tasks``, only pairs whose first word some question asks for are counted and moved.
    """
    ws = words(F.lower(F.col(text_col)))
    weight = F.lit(float(weight)) if isinstance(weight, (int, float)) else weight
    pairs = corpus.select(*by, weight.alias("weight"), F.explode(ngrams(ws, 2)).alias("g"))
    pairs = pairs.select(*by, "weight", F.split("g", " ")[0].alias("w1"), F.split("g", " ")[1].alias("w2"))
    counted = pairs.groupBy(*by, "w1", "w2").agg(F.sum("weight").alias("c2"))  # combined first, so that pairs move counted
    if tasks is not None:
        counted = counted.join(tasks.select("w1").distinct(), "w1", "left_semi")
    return counted.select(*by, "w1", "w2", "c2", F.sum("c2").over(Window.partitionBy(*by, "w1")).alias("c1"))


def evaluate(model: DataFrame, tasks: DataFrame, by: Sequence[str] = (), groups: DataFrame | None = None) -> DataFrame:
    """``(by..., task, n, acc, chance)`` of picking candidate 0 by smoothed log likelihood, ties to the larger choice.

    ``groups`` lists the values of ``by`` (a small table), so that a corpus without any known pair is judged as well.
    Questions move once for all groups: a pair has a column for each group, and a pair that
    a corpus lacks has one fixed likelihood, so only what known pairs differ from it is summed.
    """
    named = _named(groups if groups is not None else model, by)
    over = _over(F.col("c2"), F.col("c1"))
    wide = model.withColumn("over", over).groupBy("w1", "w2").agg(*[F.sum(F.when(_is_one(by, vs), F.col("over"))).alias(f"o{i}") for i, vs in enumerate(named)])
    return _answered(wide, tasks, by, named)


def compare(corpus: DataFrame, tasks: DataFrame, by: Sequence[str], weight: Column | float = 1.0, text_col: str = "text") -> DataFrame:
    """``evaluate`` of ``train`` for many corpora that have most of their texts in common.

    A text is cut into words once for all corpora, with a column for each that says how often it is
    read there; so is a pair, and only pairs that some question has go on.
    """
    named = _named(corpus, by)
    if not named:
        return evaluate(train(corpus, tasks, by, weight, text_col), tasks, by)
    at = range(len(named))
    weight = F.lit(float(weight)) if isinstance(weight, (int, float)) else weight
    parts = int(corpus.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = corpus.select(F.lower(F.col(text_col)).alias("text"), *[F.when(_is_one(by, vs), weight).alias(f"t{i}") for i, vs in enumerate(named)])
    texts = rows.repartition(parts, "text").groupBy("text").agg(*[F.sum(f"t{i}").alias(f"t{i}") for i in at])
    none = F.array().cast("array<struct<w1:string,w2:string>>")
    two = let(words(F.col("text")), lambda w: F.when(F.size(w) >= 2, F.transform(F.sequence(F.lit(1), F.size(w) - 1), lambda i: F.struct(F.get(w, i - 1).alias("w1"), F.get(w, i).alias("w2")))).otherwise(none))
    pairs = texts.select(*[f"t{i}" for i in at], F.inline(two)).where("w1 is not null and w2 is not null")
    c2 = pairs.groupBy("w1", "w2").agg(*[F.sum(f"t{i}").alias(f"t{i}") for i in at])
    c1 = c2.groupBy("w1").agg(*[F.sum(f"t{i}").alias(f"f{i}") for i in at])
    asked = tasks.where("w1 is not null and w2 is not null").select("w1", "w2").distinct()
    wide = c2.join(asked, ["w1", "w2"], "left_semi").join(c1, "w1").select("w1", "w2", *[_over(F.col(f"t{i}"), F.col(f"f{i}")).alias(f"o{i}") for i in at])
    return _answered(wide, tasks, by, named)


def _named(groups: DataFrame, by: Sequence[str]) -> list[tuple]:
    return sorted((tuple(r) for r in groups.select(*by).distinct().collect()), key=repr) if by else [()]


def _is_one(by: Sequence[str], vs: tuple) -> Column:
    return reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.lit(v)) for c, v in zip(by, vs, strict=True)], F.lit(True))


def _unknown() -> Column:
    return F.log(F.lit(SMOOTH) / F.lit(SMOOTH * VOCABULARY))


def _over(c2: Column, c1: Column) -> Column:
    """By how much the log likelihood of a known pair is over that of an unknown one."""
    return F.log((c2 + SMOOTH) / (c1 + SMOOTH * VOCABULARY)) - _unknown()


def _answered(wide: DataFrame, tasks: DataFrame, by: Sequence[str], named: list[tuple]) -> DataFrame:
    """``evaluate`` for pairs ``(w1, w2, o0, o1...)``, a column for each group."""
    at = range(len(named))
    unknown = _unknown()
    got = tasks.join(wide, ["w1", "w2"], "left")
    sums = got.groupBy("task", "key", "asks", "id", "choice").agg(F.count("w1").alias("n"), F.count("*").alias("times"), *[F.coalesce(F.sum(f"o{i}"), F.lit(0.0)).alias(f"o{i}") for i in at])
    w = Window.partitionBy("task", "key")
    own = lambda c: F.col(c) + F.col("times") * F.coalesce(F.sum(F.when(~F.col("asks"), F.col(c))).over(w), F.lit(0))
    each = sums.select("task", "id", "choice", "asks", own("n").alias("n"), *[own(f"o{i}").alias(f"o{i}") for i in at]).where("asks")
    scored = each.groupBy("task", "id", "choice").agg(*[F.round(F.sum(f"o{i}") / F.sum("n") + unknown, 6).alias(f"s{i}") for i in at])
    best = scored.groupBy("task", "id").agg(F.count("*").alias("k"), *[F.max(F.struct(f"s{i}", "choice"))["choice"].alias(f"b{i}") for i in at])
    out = best.groupBy("task").agg(F.count("*").alias("n"), F.round(F.avg(1 / F.col("k")), 6).alias("chance"), *[F.round(F.avg((F.col(f"b{i}") == 0).cast("double")), 6).alias(f"a{i}") for i in at])
    if not named:
        return out.select(*[F.lit(None).alias(c) for c in by], "task", "n", F.lit(None).cast("double").alias("acc"), "chance").where("false")
    one = F.array(*[F.struct(*[F.lit(v).alias(c) for c, v in zip(by, vs, strict=True)], F.col(f"a{i}").alias("acc")) for i, vs in enumerate(named)])
    return out.select("task", "n", "chance", F.explode(one).alias("x")).select(*[F.col(f"x.{c}") for c in by], "task", "n", "x.acc", "chance")


def category() -> Column:
    """The category of column ``task``."""
    return F.create_map(*[F.lit(x) for kv in CATEGORIES.items() for x in kv])[F.col("task")]
