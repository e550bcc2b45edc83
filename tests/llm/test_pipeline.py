import re

import corpus_pipeline
from windowforge.llm.common import materialize
from windowforge.llm.secret_scan import candidates

from .test_jaccard import brute

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, held = docs.columns, []
    for name, stage in corpus_pipeline.STAGES:
        before = {r.doc_id: r.text for r in docs.collect()} if name != "packing" else before_of(docs)
        docs = materialize(stage(spark, docs, SF), f"test-{name}")
        held.append(docs.count())
        if name == "packing":
            assert {r.doc_id for r in docs.collect()} == set(before)
            continue
        assert docs.columns == columns
        after = {r.doc_id: r.text for r in docs.collect()}
        assert set(after) <= set(before)
        if name == "quality":
            labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
            right = [(labels[i] == 1) == (i in after) for i in before if i in labels]
            assert sum(right) / len(right) > 0.95
        elif name == "exact_dedup":
            first = {}
            for i in sorted(before):
                first.setdefault(before[i].lower(), i)
            assert set(after) == set(first.values())
        elif name == "near_dedup":
            assert set(after) == {i for i, (_, root) in brute(sorted(before.items())).items() if root == i}
        elif name == "secrets":
            assert set(after) == set(before)
            for i, t in after.items():
                assert t == before[i] or "[SECRET]" in t
                assert not re.search(r"AKIA[A-Z0-9]{16}|password=[0-9a-f]{18}|token = \"[0-9a-f]{40}", t)
            assert candidates("") == []


def before_of(docs):
    return {r.doc_id: r.text for r in docs.collect()}
