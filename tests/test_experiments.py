"""Experiments give what they say, and sessions do what a rehearsal expects."""

import pytest

from triplefed import experiments as x
from triplefed import workloads as w
from triplefed.engine import Config
from triplefed.sources.graphs import content_graph
from triplefed.storage import save


@pytest.fixture(scope="module")
def content(spark, sf):
    return save(content_graph(spark, sf))


LOAD = w.numbered_load(["Y3", "Y5"], 6)


def table(df):
    return [r.asDict() for r in df.collect()]


def test_numbered_instances_look_at_no_data():
    found = w.numbered_instances(w.QUERIES["W07"], 12)
    assert len(found) == 5 and all(q.patterns[3].o.startswith("region/") for q in found)
    assert w.numbered_load(["W01", "W10"], 20) == w.numbered_load(["W01", "W10"], 20)


def test_session_does_what_a_rehearsal_expects(spark, content):
    c = Config(freq=1, statistics="exact")
    e = x.session(content, LOAD, c)
    same = ("seq", "template_id", "mode", "n_modules")
    expected = x.Rehearsal(e.stats.scores, c).go(LOAD)
    assert [{k: r[k] for k in same} for r in e.log] == [{k: r[k] for k in same} for r in expected]
    assert [r["rows"] for r in e.log] == x.central_rows(e.triples, LOAD)


def test_startup_and_balance(spark, content):
    r = {t["system"]: t for t in table(x.startup(content, w.QUERIES["Y5"], 4))}
    assert r["adaptive"]["preprocessing_s"] == 0 < r["2-hop"]["preprocessing_s"] and all(t["total_s"] < t["first_answer_s"] for t in r.values())
    b = {t["system"]: t for t in table(x.balance(content, LOAD * 2, 4))}
    assert b["adaptive"]["rows"] - b["adaptive copies"]["rows"] == content.count() and 0 <= b["2-hop"]["gini"] < 1


def test_updates_in_batches_leave_copies_as_they_were(spark, content):
    r = table(x.update_throughput(content, [w.QUERIES["Y3"]], 2))
    assert [t["op"] for t in r] == ["delete", "insert"] and r[0]["triples"] == r[1]["triples"] > 0 and not r[0]["as_at_first"] and r[1]["as_at_first"]


def test_budgets_and_accuracy(spark, content):
    r = table(x.budgets(content, LOAD, (0.0, 0.05)))
    assert all(t["within"] for t in r) and r[0]["replica_rows"] == 0
    a = table(x.statistic_accuracy(content, w.CONTENT_QUERIES, ("random",), (1, 4)))
    assert a[0]["error_s"] == a[0]["error_o"] == 0 and a[0]["cores_agree"] == 1 and a[1]["error_o"] > 0
