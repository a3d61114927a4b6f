def docs_frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id bigint, text string")


#: Nulls, empty, short, repeated, tied and long texts.
EDGES = [(1, None), (2, ""), (3, "one"), (4, "one"), (4, "one"), (None, "one two three"), (6, "Ünïcode ÄÖ naïve 中文 text"), (7, "word " * 3000), (8, " \t\n "), (9, "a  b \n c")]
