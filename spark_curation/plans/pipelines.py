"""Pipelines from pages to a corpus: one narrow chain, its ablations, and the baselines."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words
from spark_curation.io import fence, stored
from spark_curation.operators import dedup, execute, postfilter, program, refiners, render, rules, scrapers, teachers

Backend = Callable[[DataFrame], DataFrame]


def policy(rendered: DataFrame, **kw) -> DataFrame:
    """The offline policy backend: programs of the stand-in teachers next to the lines they speak of."""
    return fence(teachers.refine(teachers.extract(rendered), **kw))


def policy_outputs(rendered: DataFrame, layout: str = "decision_first", **kw) -> DataFrame:
    """Rendered rows with ``output``, the policy's program as text."""
    made = policy(rendered, **kw).withColumn("output", program.serialize(layout))
    return made.select(*rendered.columns, "output")


def replay(rendered: DataFrame, outputs: DataFrame) -> DataFrame:
    """The replay backend: outputs stored by an earlier run, joined by page."""
    return rendered.join(outputs.select("page_id", "output"), "page_id", "left")


def endpoint(rendered: DataFrame, call: Callable[[list[str]], list[str]], batch: int = 16) -> DataFrame:
    """A model behind ``call``, which takes a batch of prompts; one client for each worker."""
    from collections.abc import Iterator

    import pyarrow as pa

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            prompts = b.column(1).to_pylist()
            out = [x for i in range(0, len(prompts), batch) for x in call(prompts[i : i + batch])]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.string())], ["page_id", "output"])

    asked = rendered.select("page_id", render.number_lines(F.col("lines")).alias("prompt")).mapInArrow(run, "page_id long, output string")
    return replay(rendered, asked)


def rendered_pages(pages: DataFrame, **kw) -> DataFrame:
    """Admitted pages with their lines; pages that are rendered already are taken as they are."""
    rendered = pages if "blocks" in pages.columns else fence(render.render_pages(pages, with_blocks=True, **kw))
    return render.admit(rendered.select("page_id", "url", "lines", "blocks", "n_lines", "n_chars", "n_tokens")).where("skip_reason is null").drop("skip_reason")


def programs(pages: DataFrame, backend: Backend = policy_outputs) -> DataFrame:
    """Parsed programs next to their lines, through the text form that a model would write."""
    return fence(program.parse(fence(backend(rendered_pages(pages)).drop("blocks"))))


def curate(pages: DataFrame, backend: Backend = policy_outputs, disable: tuple[str, ...] = (), deduplicate: bool = True) -> DataFrame:
    """``(page_id, verdict, provenance, text, n_tokens)``: the whole pass over a pool, leaks out before grams get owners."""
    out = execute.run(programs(pages, backend), disable).where("text is not null")
    out = postfilter.reject_leaks(out).select("page_id", "verdict", "provenance", "text", count_words(F.col("text")).alias("n_tokens"))
    return dedup.survivors(out, dedup.ngram(out, id_col="page_id"), "page_id") if deduplicate else out


def raw(pages: DataFrame) -> DataFrame:
    """Default scrape without cleaning."""
    return scrapers.tagdrop(pages)


def cascade(scraper: Callable[[DataFrame], DataFrame], cleaner: str) -> Callable[[DataFrame], DataFrame]:
    """A scraper followed by a rule stack (a, b, c), a refiner or the chunk router."""
    return lambda pages: cleaned(fence(scraper(pages)), cleaner)


def cleaned(texts: DataFrame, cleaner: str) -> DataFrame:
    """Scraped texts after a rule stack, a refiner or the chunk router."""
    by = {"chunkprog": refiners.chunkprog, "lineprog": refiners.lineprog, "orchestrated": refiners.orchestrated}
    return fence((by[cleaner](texts) if cleaner in by else rules.apply(texts, cleaner)).select("page_id", "text")).where("text is not null and text <> ''")


def unified(pages: DataFrame) -> DataFrame:
    return curate(pages, deduplicate=False).select("page_id", "text")


#: What comes after the default scrape in the pipelines that start with it.
CLEANERS = {"rules_a": "a", "rules_b": "b", "rules_c": "c", "refiner_chunkprog": "chunkprog", "refiner_lineprog": "lineprog", "orchestrated": "orchestrated"}
PIPELINES: dict[str, Callable[[DataFrame], DataFrame]] = {"raw": raw} | {k: cascade(scrapers.tagdrop, c) for k, c in CLEANERS.items()} | {"unified": unified}


def corpora(pages: DataFrame, names: list[str] | None = None, deduplicate: bool = True) -> DataFrame:
    """``(pipeline, page_id, text, n_tokens)`` of several pipelines over the same pages, each deduplicated by itself."""
    out = None
    pages = stored(render.render_pages(pages, with_blocks=True))  # rendered once for all pipelines
    scraped = stored(raw(pages))
    for name in names or list(PIPELINES):
        part = scraped if name == "raw" else cleaned(scraped, CLEANERS[name]) if name in CLEANERS else PIPELINES[name](pages)
        part = part.select(F.lit(name).alias("pipeline"), F.col("page_id"), "text", count_words(F.col("text")).alias("n_tokens"))
        out = part if out is None else out.unionByName(part)
    if not deduplicate:
        return out
    out = stored(out)  # read by the owners of grams and again by what is left
    fell = dedup.fallen(out, names or list(PIPELINES), "pipeline", id_col="page_id").withColumnRenamed("id", "page_id")
    return out.join(fell, ["pipeline", "page_id"], "left_anti")
