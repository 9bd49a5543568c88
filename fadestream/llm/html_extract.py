r"""Main text of web pages by sum-product on the DOM (see page_model): one scan, no exchange.

Results for odd input: null or empty html gives the empty text; markup that isn't well formed is closed as browsers do;
text outside any element is judged like other runs; repeated rows are answered row by row; a null url stays null; an empty
table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import slices
from .page_model import main_texts, trained

#: Pages whose messages pass together, and characters of html among them.
TOGETHER, TOGETHER_CHARS = 256, 4_000_000


def main_content(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: a row per input row."""
    weights = pages.sparkSession.sparkContext.broadcast(trained())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sources = [x or "" for x in b.column(2).to_pylist()]
            texts: list[str] = []
            lo = 0
            while lo < len(sources):
                hi, size = lo, 0
                while hi < len(sources) and hi - lo < TOGETHER and (hi == lo or size + len(sources[hi]) <= TOGETHER_CHARS):
                    size += len(sources[hi])
                    hi += 1
                texts += main_texts(sources[lo:hi], weights.value)
                lo = hi
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    schema = pages.select("page_id", "url").schema.add("text", "string").add("n_chars", "long")
    return pages.select("page_id", "url", "html").mapInArrow(run, schema)
