"""op8: main text of every page. SQL can't parse or cut pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangecut.llm import html_text
from rangecut.llm.shared import table


def op8_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url", "html")
    return html_text.extract(pages, html_text.fit(pages))


QUERIES = {"op8_html_extract": op8_html_extract}
ORACLE_SQL: dict[str, str] = {}
