import pytest
from pyspark.sql import functions as F

from filekind.functions import text

CASES = [
    ("a=b", ["a", "=", "b"]), ("foo_bar(x);", ["foo_bar", "(", "x", ")", ";"]), ("", []), (" \t\n\r\f\x0b", []), ("!!", ["!", "!"]), ("é=b", ["\x1a", "=", "b"]),
    ("If if", ["If", "if"]), (None, []), ("éé ü", ["\x1a\x1a", "\x1a"]), ("a\x01b", ["a\x01b"]), ("日本😀", ["\x1a\x1a\x1a"]),
]


@pytest.mark.parametrize(("source", "want"), CASES)
def test_tokens(spark, source, want):
    df = spark.createDataFrame([(source,)], "s string")
    assert df.select(text.tokens_of(F.col("s"))).first()[0] == want


def test_byte_unit(spark):
    df = spark.createDataFrame([("aé日😀b",)], "s string")
    assert df.select(text.to_ascii(F.col("s"), "byte")).first()[0] == "a" + "\x1a" * 9 + "b"
    with pytest.raises(ValueError, match="unit"):
        text.to_ascii(F.col("s"), "word")


def test_tokens_join_to_the_text_without_space(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet").select("text", F.array_join(text.tokens_of(F.col("text")), "").alias("j"))
    import re

    assert all(r.j == re.sub(r"[ \t\n\r\f\x0b]", "", re.sub(r"[^\x00-\x7f]", "\x1a", r.text)) for r in d.collect())


def test_trim_and_ngrams(spark):
    df = spark.createDataFrame([(list("abcdefghijklmno"),), (["a"],), ([],)], "t array<string>")
    assert [r[0] for r in df.select(text.trim(F.col("t"))).collect()] == [[], [], []]
    assert [r[0] for r in df.select(text.trim(F.col("t"), 1, 12)).collect()] == [["b", "c"], [], []]
    assert [r[0] for r in df.select(text.trim(F.col("t"), fraction=0.2)).collect()] == [list("defghijkl"), ["a"], []]
    assert [r[0] for r in df.select(text.ngrams(F.col("t"), 3)).collect()] == [[" ".join("abcdefghijklmno"[i : i + 3]) for i in range(13)], [], []]
    assert [r[0] for r in df.select(text.ngrams(F.col("t"), 1)).collect()][1] == ["a"]


def test_names_and_ratio(spark):
    df = spark.createDataFrame([("a.py",), (".bashrc",), ("x",), ("a.b.PY",), ("d/.x",), ("a.",), ("d.x/y",)], "n string")
    assert [r[0] for r in df.select(text.extension(F.col("n"))).collect()] == ["py", None, None, "PY", None, None, None]
    df = spark.createDataFrame([("ab\x00\x01",), ("",), ("é",), ("a\t\n",)], "s string")
    assert [r[0] for r in df.select(text.nonprintable_ratio(F.col("s"))).collect()] == [0.5, None, 1.0, 0.0]
    assert [r[0] for r in df.select(text.nonprintable_ratio(F.encode("s", "UTF-8"), binary=True)).collect()] == [0.5, None, 1.0, 0.0]
