"""Queries read their tables whole."""

from conftest import SF
from pyspark.sql import functions as F

from repeatfold.workloads import methods


def test_audit_reads_long_documents(spark):
    long = methods.load_table(spark, SF, "documents").where(F.length("text") > 3000).count()
    assert long > 0 and methods._audited(spark, SF).where("n > 3000").count() == long


def test_longest_repeats_of_all_turns(spark):
    def longest(text):
        n = len(text) - 1
        while n and len({text[i : i + n] for i in range(len(text) - n + 1)}) == len(text) - n + 1:
            n -= 1
        return n

    turns = methods.load_table(spark, SF, "conversations").where("role = 'user'").collect()
    want = sorted((r["conv_id"], r["turn"], n) for r in turns if r["text"] and (n := longest(r["text"])) > 0)
    assert any(len(r["text"]) > 200 for r in turns if r["text"])
    assert sorted(map(tuple, methods.longest_repeat_all_turns(spark, SF).select("conv_id", "turn", "lr_len").collect())) == want
