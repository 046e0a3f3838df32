import importlib
import random
import subprocess
import sys
from collections import Counter
from pathlib import Path

import pytest
from tokenizers import Tokenizer

from tests.llm.helpers import EDGE, SCHEMA, empty_docs
from tests.llm.test_operators import components_by_definition, prose
from treeloom.llm.queries import VOCABULARY, oracle_sql, queries
from treeloom.llm.quality import BASE, RULES, Measured

pipeline = importlib.import_module("corpus_pipeline")


def corpus(rng):
    rows = []
    for i in range(60):
        rows.append([i, "\n".join(prose(rng, 40) for _ in range(3)), "en", "big" if i < 40 else "small", 0])
    for i in range(60, 72):
        rows.append([i, rows[5][1] if i % 2 else rows[6][1].replace("a", "A"), "en", "big", 0])
    rows.append([72, "too short", "en", "big", 0])
    rows.append([73, "bad### " * 80, "en", "small", 0])
    return rows


def test_stages_against_brute_force(spark, small):
    rows = corpus(random.Random(2))
    docs = spark.createDataFrame([tuple(r) for r in rows], SCHEMA).repartition(3)
    good = pipeline.STAGES[0][1](spark, docs, small)
    text = {r[0]: r[1] for r in rows}
    kept = {d for d, t in text.items() if not BASE.rejects(Measured(t)) and not any(r.rejects(Measured(t)) for r in RULES)}
    assert {r["doc_id"] for r in good.collect()} == kept and 72 not in kept and 73 not in kept
    lined = pipeline.STAGES[1][1](spark, good, small)
    out = {r["doc_id"]: r["text"] for r in lined.collect()}
    # copies that five or more documents hold lose their lines and go, the first stays whole
    assert all(out[i] == text[i] for i in range(60)) and not any(i in out for i in range(60, 72) if i % 2)
    unique = pipeline.STAGES[2][1](spark, good, small)
    order = sorted(kept)
    want = {order[i] for i, (_, c) in enumerate(components_by_definition([text[d] for d in order], 5, 80)) if c == i}
    assert {r["doc_id"] for r in unique.collect()} == want
    mixed = Counter(r["doc_id"] for r in pipeline.STAGES[3][1](spark, unique, small).collect())
    assert set(mixed) == want and max(mixed.values()) <= 3 and all(n == 1 for d, n in mixed.items() if d < 40)
    lib = Tokenizer.from_file(VOCABULARY)
    done = {r["doc_id"]: r["n_tokens"] for r in pipeline.STAGES[4][1](spark, unique, small).collect()}
    assert done == {d: len(lib.encode(text[d], add_special_tokens=False).ids) for d in want}


def test_stages_keep_the_columns_and_stand_awkward_rows(spark, small):
    for name, stage in pipeline.STAGES:
        for docs in (empty_docs(spark), spark.createDataFrame(EDGE, SCHEMA)):
            out = stage(spark, docs, small)
            assert out.count() >= 0
            if name != pipeline.STAGES[-1][0]:
                assert out.columns == pipeline.COLUMNS and [t for _, t in out.dtypes] == [t for _, t in docs.dtypes]


def test_run_on_a_table(spark, small):
    assert pipeline.run(spark, small).count() > 0


@pytest.mark.parametrize("name", sorted(queries()))
def test_queries_run_and_match_their_sql(spark, small, name):
    import duckdb

    from tests.test_queries import rows_of

    got = queries()[name](spark, small).toPandas()
    if name in oracle_sql():
        c = duckdb.connect()
        for t in ("documents", "embeddings", "pages"):
            c.sql(f"create view {t} as select * from read_parquet('{small}/{t}.parquet')")
        assert rows_of(got) == rows_of(c.sql(oracle_sql()[name]).df())
    assert len(got) > 0


def test_nothing_else_imports_the_subpackage():
    root = Path(__file__).resolve().parents[2]
    for f in (root / "treeloom").rglob("*.py"):
        if "llm" not in f.parts:
            assert "treeloom.llm" not in f.read_text(), f


def test_entry_module_without_the_subpackage(tmp_path):
    root = Path(__file__).resolve().parents[2]
    code = "import sys; sys.modules['treeloom.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and not any(k.startswith('op3_') for k in q); assert len(q) > 100"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True)
