"""A small table with every awkward case: nulls, empty and long texts, copies, repeated rows, clashing columns."""

import random

from pyspark.sql import DataFrame, SparkSession

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, digest string, bucket int, fp bigint, ids string, features string, label int"


def words(rng: random.Random, n: int) -> str:
    return " ".join("".join(rng.choice("abcdeéß漢😀XYZ,.!") for _ in range(rng.randrange(1, 9))) for _ in range(n))


def texts(seed: int = 1) -> list:
    rng = random.Random(seed)
    shared = words(rng, 120)
    base = [words(rng, rng.randrange(5, 200)) for _ in range(20)]
    out = [None, "", " ", "\n\n", "x", "The " * 700, "a" * 3000, "=" * 500, "Tab\there  double \n\nspaces\r\n end\x0b", "<|endoftext|> in <|startoftext|>text<|endoftext|>", "don't we'll 's 1234 ¼ ٣"]
    out += base + base[:5] + [base[0] + " " + shared, shared + " " + base[1], "pre " + shared + " post", base[2][:-3] + "zzz", words(rng, 9000)]
    return out


def table(spark: SparkSession, rows: list | None = None) -> DataFrame:
    found = texts() if rows is None else rows
    data = [(i, t, "en", f"s{i % 3}", None if t is None else len(t), "clash", 7, 7, "clash", "clash", 7) for i, t in enumerate(found)]
    return spark.createDataFrame(data, SCHEMA).repartition(3)


def empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], SCHEMA)


def with_repeats(spark: SparkSession) -> DataFrame:
    """The rows twice, and a null id."""
    t = table(spark)
    return t.unionByName(t).unionByName(spark.createDataFrame([(None, "a row without an id", None, None, None, None, None, None, None, None, None)], SCHEMA))
