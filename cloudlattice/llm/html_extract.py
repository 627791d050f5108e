"""Main text of web pages: blocks, labelled by the recurrent labeller, joined in page order."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.llm.html_blocks import blocks
from cloudlattice.llm.html_model import Params, inputs, probabilities, restore
from cloudlattice.llm.work import load

LIMIT = 0.5


@lru_cache(1)
def model() -> Params:
    return restore()


def main_texts(pages: Iterable[str | None], params: Params | None = None, limit: float = LIMIT) -> list[str]:
    """The text of each page; empty for null, for pages without blocks and for those without main text."""
    found = [blocks(p) for p in pages]
    likely = probabilities(params or model(), [[inputs(b) for b in page] for page in found])
    return ["\n".join(b.text for b, q in zip(page, prob, strict=True) if q >= limit) for page, prob in zip(found, likely, strict=True)]


def extract(pages: DataFrame, html_col: str = "html", limit: float = LIMIT) -> DataFrame:
    """The input's rows and columns with ``main_text``.

    A null page gives an empty text; broken markup is read as far as it goes; pages of
    any length are read whole; repeated rows give equal texts; an empty table gives an
    empty result; a column named ``main_text`` in the input is replaced.
    """

    @F.pandas_udf("string")
    def main_text(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            parts = [main_texts(batch.iloc[at : at + 256], limit=limit) for at in range(0, len(batch), 256)]
            yield pd.Series([t for part in parts for t in part], dtype=object)

    return pages.withColumn("main_text", main_text(F.col(html_col).cast("string")))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = extract(load(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return got.select("page_id", "url", F.col("main_text").alias("text"), F.char_length("main_text").cast("long").alias("n_chars"))
