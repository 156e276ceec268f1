import __spark_entry__ as entry


def test_entry_runs_and_names_match(spark):
    assert entry.entry(spark).count() == 20
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_nothing_outside_imports_the_corpus_operators():
    from pathlib import Path

    root = Path(entry.__file__).parent
    for f in (root / "patternwalk").rglob("*.py"):
        if "llm" not in f.parts:
            assert "patternwalk.llm" not in f.read_text()


def test_the_package_travels_where_workers_lack_it(spark, monkeypatch):
    from patternwalk.plans import ship

    sent = []
    monkeypatch.setattr(ship, "reachable", lambda: False)
    monkeypatch.setattr(ship, "_SENT", set())
    monkeypatch.setattr(type(spark.sparkContext), "addPyFile", lambda self, path: sent.append(path))
    ship.ship(spark)
    ship.ship(spark)
    assert len(sent) == 1 and sent[0].endswith("patternwalk.zip")


def test_moved_queries_read_their_tables(spark):
    """These two made their data up; every user and event of the given table counts."""
    from patternwalk import workloads
    from patternwalk.sources import builders
    from patternwalk.sources.tables import table

    sf = "/root/testdata/sf0.001"
    events = table(spark, sf, "events")
    gates = workloads.QUERIES["as_of_checkpoint"](spark, sf)
    assert gates.select("event_id").exceptAll(events.select("event_id")).count() == 0 and gates.count() == events.count()
    own = {(r.user_id, r.event_id): r for r in events.collect()}
    for r in gates.collect():
        before = [e for e in own.values() if e.user_id == r.user_id and e.event_type == "purchase" and (e.ts, e.event_id) <= (own[r.user_id, r.event_id].ts, r.event_id)]
        assert r.checkpoint == (max(before, key=lambda e: (e.ts, e.event_id)).event_id if before else None)
    db = builders.synthetic_on(spark, sf)
    assert workloads.QUERIES["db_stats_synthetic"](spark, sf).first().n_vertices == events.count()
    from patternwalk.model import validate

    assert validate(db).count() == 0
