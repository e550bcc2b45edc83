"""The method's expressions and table functions under SQL names. Scalar ones are SQL functions, which the optimiser inlines."""

from __future__ import annotations

import hashlib

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

SCALARS = {
    "wf_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    "wf_cosine": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "CASE WHEN wf_dot(a, a) > 0 AND wf_dot(b, b) > 0 THEN wf_dot(a, b) / (sqrt(wf_dot(a, a)) * sqrt(wf_dot(b, b))) ELSE 0D END"),
    "wf_pack_score": ("cos DOUBLE, remaining INT, length INT, w INT", "DOUBLE", "cos + remaining / w + CASE WHEN length <= remaining THEN 1D ELSE w / (w + length - remaining) END"),
    "wf_lr": ("step BIGINT, total BIGINT", "DOUBLE", "CASE WHEN step < 1000 THEN step * 3e-7D ELSE 1.5e-4D * (1 + cos(pi() * least(1D, (step - 1000) / (total - 1000)))) END"),
    "wf_edit_sim": ("a STRING, b STRING", "DOUBLE", "CASE WHEN greatest(length(a), length(b)) > 0 THEN 1 - levenshtein(a, b) / greatest(length(a), length(b)) ELSE 1D END"),
}


@udtf(returnType="seg_no int, start int, tokens array<string>")
class Segments:
    """The pieces of a list of tokens, at most w long."""

    def eval(self, tokens: list, w: int):
        for k in range(0, max(len(tokens or []), 1), w):
            yield k // w, k, (tokens or [])[k : k + w]


@udtf(returnType="place int, word string")
class Needle:
    """A text with a needle of words put at a depth (percent) of its first ``length`` words, a row per word."""

    def eval(self, text: str, needle: str, depth: int, length: int):
        words, own = (text or "").split(), (needle or "").split()
        room = max(length - len(own), 0)
        at = room * depth // 100
        for place, word in enumerate((words[:at] + own + words[at:room])):
            yield place, word


@udtf(returnType="place int, key string, value string, asked boolean")
class KvExample:
    """The pairs of a key-value example, a row each, and which one is asked for."""

    def eval(self, example: int, pairs: int, position: int):
        made = lambda what, i: hashlib.md5(f"{what}:{example}:{pairs}:{i}".encode()).hexdigest()
        for i in range(1, pairs + 1):
            yield i, made("k", i), made("v", i), i == position


def register_all(spark: SparkSession) -> None:
    for name, (args, result, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {result} RETURN {body}")
    spark.udtf.register("wf_segments", Segments)
    spark.udtf.register("wf_needle", Needle)
    spark.udtf.register("wf_kv_example", KvExample)
