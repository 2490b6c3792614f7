"""Every operator and stage over nulls in any column, repeated rows, a long text, clashing column names, and empty tables."""

import corpus_pipeline
import pytest
from freshview.llm import registry
from freshview.llm.common import materialise
from pyspark.sql import functions as F

CLASHES = ("n", "sid", "h", "prefix", "score", "lang_pred", "shard", "slot", "leaf", "key", "ids", "items", "spans", "secret_spans", "row", "opening", "block", "host", "template", "turns", "media")
FOX = "The quick brown fox jumps over the lazy dog again and again"
TABLES = {
    "documents": ("doc_id long, text string, lang string, source string, n_chars long", [(1, FOX, "en", "s", 59), (None, "le chat noir est dans la maison de la mère", None, None, None), (2, None, "en", "s", None), (3, "", None, "s", 0), (4, "token=abcdefgh12345 " + "x" * 100000, "en", None, 5), (1, FOX, "en", "s", 59)]),
    "pages": ("page_id long, url string, html string", [(1, "http://a.b/c", "<p>x</p>"), (None, None, None), (2, "::bad::", ""), (2, "http://a.b/c", "<p>x</p>")]),
    "benchmark": ("item_id long, text string", [(1, "quick brown fox jumps over the lazy dog again and again"), (None, "le chat"), (2, None)]),
    "conversations": ("conv_id long, turn long, role string, text string", [(1, 0, "user", "a"), (1, 1, "assistant", "b"), (2, 0, "user", "a"), (None, None, None, None), (3, None, "user", None)]),
}
ROWS = {"op1_page_text": 4, "op9_preference_pairs": 4}


@pytest.fixture(scope="module")
def folders(spark, tmp_path_factory):
    odd, empty = str(tmp_path_factory.mktemp("odd")), str(tmp_path_factory.mktemp("empty"))
    for name, (schema, rows) in TABLES.items():
        df = spark.createDataFrame(rows, schema).withColumns({c: F.lit(7) for c in CLASHES})
        df.write.parquet(f"{odd}/{name}.parquet")
        df.limit(0).write.parquet(f"{empty}/{name}.parquet")
    return odd, empty


@pytest.mark.parametrize("name", sorted(registry.queries()))
def test_operator(spark, folders, name):
    odd, empty = folders
    assert registry.queries()[name](spark, odd).count() == ROWS.get(name, 6)
    assert registry.queries()[name](spark, empty).count() == 0


def test_pipeline(spark, folders):
    odd, empty = folders
    now = spark.read.parquet(f"{odd}/documents.parquet")
    columns, counts = now.columns, []
    for name, stage in corpus_pipeline.STAGES:
        now = materialise(stage(spark, now, odd))
        counts.append(now.count())
        assert name == "tokens" or now.columns == columns
    # null and empty texts go, then the repeated row; cutting the passage leaves words of the first
    assert counts == [4, 3, 3, 3, 3]
    assert corpus_pipeline.run(spark, empty).count() == 0
