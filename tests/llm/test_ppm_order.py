from pyspark.sql import functions as F

from blockgraph.llm import ppm


def test_default_is_order_six(spark):
    # six bytes before a digit tell it, five do not
    rows = [(i, ("abcdef" + "1" if i % 2 else "xbcdef" + "2") * 4) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    of = lambda *order: {r.doc_id: r.score for r in ppm.score(df, F.col("doc_id") > 3, *order).collect()}
    default, six, five = of(), of(6), of(5)
    assert default == six
    assert sum(six.values()) > sum(five.values())
