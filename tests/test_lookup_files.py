"""Lookups in tables of several files, without the fold for few files."""

from dataclasses import replace
from pathlib import Path

from widefeat import registry, worlds
from widefeat.plans import translate


def test_tables_of_several_files(spark, small_dir, tmp_path):
    """As the index narrows it, a snapshot has a table once for each of its files, all under one phys_id."""
    engine = worlds.world(spark, small_dir, "web")
    snap, columns = engine.catalog.snapshot("web"), ["char_len", "lang_guess", "quality", "raw"]
    ids = registry.some_ids(spark, small_dir, 20)
    physical = []
    for k, p in enumerate(snap.physical):
        if p.purpose == "features" and "char_len" in map(translate.logical_name, p.columns):
            spark.read.parquet(p.path).repartition(3).write.parquet(folder := f"{tmp_path}/{k}")
            physical += [replace(p, path=str(f), files=1) for f in sorted(Path(folder).glob("*.parquet"))]
        else:
            physical.append(p)
    assert len(physical) > len(snap.physical)
    got = translate.assemble(spark, replace(snap, physical=tuple(physical)), columns, None, ids).relation
    want = translate.assemble(spark, snap, columns, None, ids).relation
    rows = lambda df: sorted(map(str, df.select("entity_id", *columns).collect()))
    assert rows(got) == rows(want) and len(rows(want)) == 20


def test_ids_of_null_texts_are_not_looked_up(spark, tmp_path):
    spark.createDataFrame([(1, "a"), (2, None), (3, "b")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert len(registry.some_ids(spark, str(tmp_path), 20)) == 2 and None not in registry.some_ids(spark, str(tmp_path), 1)
