import corpus_pipeline


def test_stages_send_small_batches(spark):
    """Every stage lowers the rows of a batch for Python workers, and leaves a smaller setting alone."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    docs = spark.createDataFrame([(1, "mail a1@b.org", "en", "web")], "doc_id long, text string, lang string, source string")
    try:
        for given, used in (("10000", "1000"), ("0", "1000"), ("200", "200")):
            spark.conf.set(name, given)
            stage = dict(corpus_pipeline.STAGES)["pii"]
            sizes = stage(spark, docs, "").count()
            assert (sizes, spark.conf.get(name)) == (1, used)
    finally:
        spark.conf.set(name, before)
