"""SQL surface: table functions for lines and program items, and a native function for the prompt form."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="lid int, text string, zone string")
class PageLines:
    """``SELECT ... FROM pages, LATERAL page_lines(html)``."""

    def eval(self, html: str) -> Iterator[tuple]:
        from spark_curation.operators.render import parse_blocks

        for i, (text, zone) in enumerate(parse_blocks(html)):
            yield i + 1, text, zone


@udtf(returnType="kind string, a int, b int, frag string")
class ProgramItems:
    """``SELECT ... FROM outputs, LATERAL program_items(output)``: removals and cuts of a program in order."""

    def eval(self, output: str) -> Iterator[tuple]:
        import json
        import re

        from spark_curation.operators.program import CUT_ITEM, LINE_ITEM

        for line in (output or "").split("\n"):
            if m := re.match(LINE_ITEM, line):
                yield "rm", int(m[1]), int(m[2] or m[1]), None
            elif m := re.match(CUT_ITEM, line):
                yield "sub", int(m[1]), int(m[1]), json.loads(m[2])


def register(spark: SparkSession) -> None:
    """Makes the functions known to ``spark.sql``."""
    spark.udtf.register("page_lines", PageLines)
    spark.udtf.register("program_items", ProgramItems)
    # one program run over its lines: removals of the extraction block, then those of an edit; deletes give null, rewrites their body
    item = r"(?m)^[ \\t]*rm[ \\t]+([0-9]{1,6})(?:-([0-9]{1,6}))?[ \\t]*$"
    gone = f"""flatten(transform(regexp_extract_all(block, r'{item}', 0), x -> sequence(cast(regexp_extract(x, r'{item}', 1) AS INT), cast(coalesce(nullif(regexp_extract(x, r'{item}', 2), ''), regexp_extract(x, r'{item}', 1)) AS INT))))"""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION removed_lines(block STRING) RETURNS ARRAY<INT> RETURN {gone}")
    verdict = "regexp_extract(output, '^\\\\s*<(keep|delete|edit|rewrite)>', 1)"
    payload = "regexp_extract(output, '(?s)<extract>(.*?)<(?:keep|delete|edit|rewrite)>(.*)$', {})"
    kept = f"nullif(array_join(transform(filter(transform(lines, (x, i) -> struct(i + 1 AS lid, x AS x)), p -> NOT array_contains(concat(removed_lines({payload.format(1)}), CASE WHEN {verdict} = 'edit' THEN removed_lines({payload.format(2)}) ELSE cast(array() AS ARRAY<INT>) END), p.lid)), p -> p.x), '\\n'), '')"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION run_program(lines ARRAY<STRING>, output STRING) RETURNS STRING RETURN CASE {verdict} WHEN 'delete' THEN NULL WHEN 'rewrite' THEN nullif(regexp_replace({payload.format(2)}, r'^\\s+|\\s+$', ''), '') WHEN '' THEN NULL ELSE {kept} END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION numbered(lines ARRAY<STRING>) RETURNS STRING RETURN array_join(transform(lines, (x, i) -> concat('<lid:', i + 1, '> ', x)), '\n')")
