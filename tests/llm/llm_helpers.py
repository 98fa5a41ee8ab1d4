"""What these tests share."""

SF = "/root/testdata/sf0.001"



def table(spark, rows, schema="doc_id long, text string, lang string, source string, n_chars long"):
    return spark.createDataFrame(rows, schema)
