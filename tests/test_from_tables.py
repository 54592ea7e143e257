"""Queries whose job used to be made up: they follow the table that they are given, as their SQL does."""

import duckdb
import pytest

import __spark_entry__ as entry
from tripleschema.plans import experiments, gen
from tripleschema.queries import reasoning

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def other(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("other")
    spark.read.parquet(f"{SF}/events.parquet").where("event_type <> 'error'").write.parquet(f"{at}/events.parquet")
    spark.read.parquet(f"{SF}/supplier.parquet").write.parquet(f"{at}/supplier.parquet")
    spark.read.parquet(f"{SF}/lineitem.parquet").where("l_orderkey % 3 = 1").write.parquet(f"{at}/lineitem.parquet")
    return str(at)


def oracle(name, at):
    con = duckdb.connect()
    for t in ("events", "supplier", "lineitem"):
        files = f"{at}/{t}.parquet" if at == SF else f"{at}/{t}.parquet/*.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{files}'")
    return sorted(map(repr, con.execute(entry.oracle_sql()[name]).fetchall()))


@pytest.mark.parametrize("name", ["ops_udtf_expand", "shapes_to_schema", "trigger_pairs_events", "weak_acyclicity"])
def test_follows_the_table(spark, other, name):
    found = [sorted(repr(tuple(r)) for r in entry.queries()[name](spark, at).collect()) for at in (SF, other)]
    assert found == [oracle(name, SF), oracle(name, other)] and found[0] != found[1]


def test_sweep_draws_from_the_table(spark, other, monkeypatch):
    given = []
    monkeypatch.setattr(experiments, "existential_sweep_table", lambda s, drawn: given.append(drawn))
    for at in (SF, other):
        entry.queries()["exp_existential_sweep"](spark, at)
    assert given[0] != given[1] and all(len(x) > 1000 for x in given)
    for n in (0, 100, 200):
        made = [gen.generate(experiments.growing_existentials(n), gen.repeated(x)) for x in given]
        assert made[0] != made[1] and all(len(g.patterns) == 100 and len(g.existentials) == n for g in made)
    monkeypatch.undo()
    rows = experiments.existential_sweep_table(spark, (4,), runs=1, size=20, drawn=given[0]).collect()
    assert [r.kind for r in rows] == ["con", "con_ex"]
    with pytest.raises(ValueError):
        gen.repeated([])
