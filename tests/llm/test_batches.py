"""What goes to a Python worker at once is bounded by bytes, not by rows."""

import corpus_pipeline
import pyarrow as pa
from tracelink.llm import common


def test_stages_bound_the_bytes_of_a_batch(spark, monkeypatch):
    name, bound = "spark.sql.execution.arrow.maxBytesPerBatch", 100_000
    docs = spark.createDataFrame([(i, f"w{i} " * 1000, "en", "web", 4000) for i in range(200)], "doc_id long, text string, lang string, source string, n_chars long").coalesce(1)

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.nbytes])], names=["n"])

    monkeypatch.setattr(common, "BATCH_BYTES", bound, raising=False)
    for step, stage in corpus_pipeline.STAGES:
        if step == "mixing":  # without Python
            continue
        spark.conf.unset(name)
        stage(spark, docs, "")
        assert max(r["n"] for r in docs.mapInArrow(sizes, "n long").collect()) < 2 * bound, step
    spark.conf.unset(name)
