import __spark_entry__ as entry


def test_names_and_sql_belong_together():
    names = set(entry.queries())
    assert set(entry.oracle_sql()) <= names and len(names) >= 100


def test_flagship(spark):
    rows = entry.entry(spark).collect()
    assert {r.method for r in rows} == {"framework", "random", "graph"}
    by = {r.method: r for r in rows}
    assert by["framework"].pair_mean > by["random"].pair_mean and by["framework"].cross_attention < by["random"].cross_attention
