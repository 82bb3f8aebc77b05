"""Main text of pages: leaf blocks labelled by a linear-chain conditional random field, decoded by Viterbi.

Blocks labelled main are joined in page order by one space; white space inside a
block is one space and character references are decoded.  Nothing is capped.

Edge cases: a null or empty page, or one without main blocks, gives the empty
text; broken markup is read as far as it goes; repeated rows give equal rows;
extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import text_batches
from litspark.llm.html_blocks import leaf_blocks
from litspark.llm.html_crf import Field, features

_loaded: list[Field] = []


def main_text(page: str | None, model: Field) -> str:
    blocks = leaf_blocks(page)
    return " ".join(b.text for b, y in zip(blocks, model.decode(features(blocks))) if y)


def _extracted(rows: Iterator[pa.RecordBatch], model: Field) -> Iterator[pa.RecordBatch]:
    for batch in rows:
        for at in range(0, batch.num_rows, 512):
            part = batch.slice(at, 512)
            texts = [main_text(h, model) for h in part.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [part.column("page_id"), part.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"]
            )


def extract_pages(pages: DataFrame, model: Field | None = None) -> DataFrame:
    """One row per row of ``pages(page_id, url, html)``: page_id, url, text, n_chars."""
    text_batches(pages.sparkSession)
    shared = pages.sparkSession.sparkContext.broadcast(model or Field.load())
    source = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return source.mapInArrow(lambda rows: _extracted(rows, shared.value), "page_id long, url string, text string, n_chars long")


#: DuckDB SQL of the result on pages whose main text is the article without its headline.
ORACLE = r"""
WITH cut AS (SELECT page_id, url, regexp_extract(coalesce(html, ''), '<article>(.*)</article>', 1, 's') AS body FROM pages),
bare AS (SELECT page_id, url, regexp_replace(regexp_replace(body, '<h1>.*?</h1>', ' ', 'gs'), '<[^>]*>', ' ', 'g') AS t FROM cut),
said AS (SELECT page_id, url, replace(replace(replace(replace(t, '&quot;', '"'), '&lt;', '<'), '&gt;', '>'), '&amp;', '&') AS t FROM bare)
SELECT page_id, url, trim(regexp_replace(t, '\s+', ' ', 'g')) AS text, length(trim(regexp_replace(t, '\s+', ' ', 'g')))::BIGINT AS n_chars FROM said
"""
