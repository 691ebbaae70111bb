"""Inputs with every awkward case: nulls, empty and long texts, ties, repeated rows, clashing columns, no rows."""

CLASHES = ["words", "hashes", "prints", "fp", "rep", "block", "token", "row_id", "base_spans", "score", "key", "decoded", "n", "component", "h"]
LONG = "alpha beta gamma delta epsilon zeta " * 6000


def documents(spark, rows=None):
    rows = rows if rows is not None else [(None, "one two three four five six seven"), (1, None), (2, ""), (3, " \n\t "), (4, LONG), (5, "tie tie tie"), (5, "tie tie tie"), (6, "日本語 éà 😀"), (7, "x" * 50_000), (8, "one two three four five six seven")]
    rows = [(i, t, "en" if i != 3 else None, None, len(t or "")) for i, t in rows]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    from pyspark.sql import functions as F

    for c in CLASHES:
        df = df.withColumn(c, F.lit("clash"))
    return df
