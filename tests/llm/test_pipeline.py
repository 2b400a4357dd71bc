"""The pipeline's stages: each on the rows of the one before, its decisions in effect, clean documents kept."""

import corpus_pipeline as P
from spatial_links.llm.queries import queries

from ..conftest import DATA
from .test_operators import brute_groups


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    columns, kept = docs.columns, {}
    for name, stage in P.STAGES:
        out = stage(spark, docs, DATA)
        out.write.parquet(str(tmp_path / name))
        before = {r.doc_id: r.text for r in docs.collect()}
        docs = spark.read.parquet(str(tmp_path / name))
        kept[name] = (before, {r.doc_id: (r.text if "text" in docs.columns else None) for r in docs.collect()})
        if name != P.STAGES[-1][0]:
            assert docs.columns == columns
    before, after = kept["near_duplicates"]
    groups = brute_groups(list(before.items()), 5)
    assert set(after) == {i for i, (_, c) in groups.items() if c == i}
    before, after = kept["secret_scans"]
    assert set(before) == set(after) and all("[secret]" in after[i] for i in before if after[i] != before[i])
    before, after = kept["best_fit_packing"]
    assert set(before) == set(after)
    assert P.run(spark, DATA).count() == docs.count()


def test_names():
    assert {f"op{i}" for i in range(1, 11)} == {k.split("_")[0] for k in queries() if k.startswith("op")}
    assert [n for n, _ in P.STAGES] == ["quality_rules", "near_duplicates", "benchmark_decontamination", "secret_scans", "best_fit_packing"]
