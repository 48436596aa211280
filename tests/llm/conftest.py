import pytest
from pyspark.sql import SparkSession

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    s = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


@pytest.fixture(scope="session")
def texts(spark):
    """Every document of the small table, and texts for edge cases."""
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    odd = [
        None, "", " ", "\n\n", "one", "a b c", "A b C", "a b c d", "x" * 50_000, "w " * 9_000, "  \x0b\x0c end", "é🙂 ü\t🙂 #$%",
        "mail a@b.c_d@e.f.g. or x.y+z@mail1.example.com, 1.2.3.4.5 and 300.1.1.1 a@@b.c @x.y",
        "🙂 card 4337 1665 9846 4399 4111-1111-1111-1111 4111111111111111 +1 (988) 555-2485 +49.30.1234567 +1 + 12",
        "reach me under anna.lee (at) example (dot) org, or call me at 030-123-4567. ip 10[.]0[.]0[.]1, visa 4111.1111.1111.1111.",
        "5 " * 3_000, "1.2.3.4 " * 700, "a@b.c" * 400, "<|endoftext|> <|endoftext|>", "Released under the MIT License.",
    ]
    return rows + [(1_000_000 + i, t) for i, t in enumerate(odd)] + [rows[0], rows[0]]


@pytest.fixture(scope="session")
def docs(spark, texts):
    """Those texts with columns whose names clash with the operators' own."""
    df = spark.createDataFrame(texts, "doc_id long, text string")
    from pyspark.sql import functions as F

    more = {c: F.lit(None).cast("int") for c in ("length", "fp", "u", "part", "kind", "salt", "quality", "pii", "row", "key", "_n", "_r", "n", "rep", "ids", "s", "place", "shard")}
    return df.withColumns({"lang": F.lit("en"), "source": F.lit("src0"), "n_chars": F.length("text").cast("long")} | more).repartition(5)
