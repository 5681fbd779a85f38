import pytest


@pytest.fixture(scope="session")
def docs_schema():
    return "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="session")
def make(spark, docs_schema):
    """Frame of documents from (doc_id, text) pairs."""

    def run(rows):
        return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], docs_schema)

    return run


@pytest.fixture(scope="session")
def folder(spark, tmp_path_factory, make):
    """Writes tables into a new folder and returns its path."""

    def run(docs=(), labels=(), benchmark=(), pages=(), conversations=()):
        path = tmp_path_factory.mktemp("sf")
        make(docs).write.parquet(f"{path}/documents.parquet")
        spark.createDataFrame(list(labels), "doc_id bigint, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
        spark.createDataFrame(list(benchmark), "item_id bigint, text string").write.parquet(f"{path}/benchmark.parquet")
        spark.createDataFrame(list(pages), "page_id bigint, url string, html string").write.parquet(f"{path}/pages.parquet")
        spark.createDataFrame(list(conversations), "conv_id bigint, turn bigint, role string, text string").write.parquet(f"{path}/conversations.parquet")
        return str(path)

    return run
