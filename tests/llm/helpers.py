from pyspark.sql import functions as F

SMALL = "/root/testdata/sf0.001"


def odd_documents(spark):
    """Nulls in every column, empty and very long texts, repeated rows, and columns whose names the operators use."""
    long = "lorem ipsum dolor sit amet " * 20_000
    rows = [(1, "some plain words of a text\nand a second line of it", "en"), (1, "some plain words of a text\nand a second line of it", "en"), (2, None, None), (3, "", "en"), (None, "a text without an id, long enough to be a line", "en"), (4, long, "en"), (5, " \n\t", None), (6, "123 456", "xx")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    return df.withColumns({c: F.lit(-1) for c in ("score", "size", "spans", "fp", "ids", "line", "place", "root", "hash", "word", "lines", "kept", "n", "halves", "digest", "bytes", "refers_to", "row", "shard", "slot", "lang_pred", "label", "entry", "x", "fp_home", "value", "leaf", "part", "n_tokens", "decoded", "leak")})


def keys(df, column="doc_id"):
    return sorted((r[0] for r in df.select(column).collect()), key=lambda k: (k is not None, k))


ODD_KEYS = [None, 1, 1, 2, 3, 4, 5, 6]
