import numpy as np
from pyspark.sql import functions as F

from rowgraph.operators import baselines, board, encode, train
from rowgraph.plans import workloads
from rowgraph.queries_tasks import churn_scored
from tests.test_training import toy


def test_board(spark, sf, tmp_path):
    scored = churn_scored(spark, sf).filter("split = 'test'")
    board.append(board.evaluate(scored, "binary", "churn", "count"), f"{tmp_path}/b")
    board.append(board.evaluate(scored.withColumn("score", F.lit(0)), "binary", "churn", "base"), f"{tmp_path}/b")
    value = baselines.constant(workloads.customer_value(spark, sf)).filter("split = 'test'")
    board.append(board.evaluate(value, "regression", "value", "median"), f"{tmp_path}/b")
    got = board.show(spark, f"{tmp_path}/b").collect()
    assert [r["task"] for r in got] == ["churn", "churn", "value"] and got[0]["value"] >= got[1]["value"]


def test_text_encoders(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    assert encode.tf_idf(docs, "text", 32).select("tf_idf").first()[0].size == 32
    assert encode.word_vectors(docs, "text", 8).select("vector").first()[0].size == 8
    page = spark.createDataFrame([("<p>a<script>no()</script> b</p><!-- c -->d",)], "html string")
    assert page.select(encode.html_text("html")).first()[0] == "a b d"


def test_pretraining_and_transfer(spark):
    model, pdf = toy()
    mined, own = toy()[1].assign(label=lambda f: f["label"] * 2 + 1), toy()[0]
    df = spark.createDataFrame(mined, train.PACKED).cache()
    history = train.pretrain(model, [df], 4)
    assert history[-1] < history[0]
    assert set(train.transfer(model, own)) == set(model.params)
    assert all(np.array_equal(own.params[k], model.params[k]) for k in own.params)
    before = {k: v.copy() for k, v in own.params.items()}
    train.finetune(own, spark.createDataFrame(pdf, train.PACKED), 2, frozen=("enc", "msg"))
    assert all(np.array_equal(before[k], own.params[k]) for k in own.params if k != "head") and not np.array_equal(before["head"], own.params["head"])
