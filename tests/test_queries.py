import os

import duckdb
import pytest

from bitextspark.plans import q_training, registry
from bitextspark.sources import files

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    return con


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_query_equals_its_sql(spark, duck, name):
    got = registry.QUERIES[name](spark, SF)
    columns = sorted(got.columns)
    want = duck.sql(f"SELECT {', '.join(f'"{c}"' for c in columns)} FROM ({registry.SQL[name]})").fetchall()
    assert sorted((tuple(r[c] for c in columns) for r in got.collect()), key=str) == sorted(want, key=str)


@pytest.mark.parametrize("name", ["best_checkpoint", "best_portions", "convergence_steps", "diverse_specs", "model_ranking", "published_ladder", "sinusoid_positions", "teacher_members", "train_plans"])
def test_query_reads_a_table(spark, name):
    assert registry.QUERIES[name](spark, SF).inputFiles()


def test_ladder_reports_every_stage(spark):
    rows = q_training.ladder(spark, SF).collect()
    assert {r["stage_no"] for r in rows} == {1, 2, 3, 4, 5, 6} and all(0 <= r["bleu"] <= 100 for r in rows)


def test_files(spark, tmp_path):
    (tmp_path / "a").write_text("".join(f"s{i}\n" for i in range(500)))
    (tmp_path / "b").write_text("".join(f"t{i}\n" for i in range(500)))
    got = files.read_aligned(spark, str(tmp_path / "a"), str(tmp_path / "b")).collect()
    assert sorted((r["line"], r["src"], r["tgt"]) for r in got) == [(i, f"s{i}", f"t{i}") for i in range(500)]


def test_entry_imports_without_the_training_data_folder(tmp_path):
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/bitextspark", tmp_path / "bitextspark", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), any(n.startswith('op') for n in e.queries()))"], cwd=tmp_path, capture_output=True, text=True, env=os.environ | {"PYTHONPATH": str(tmp_path)})
    assert out.stdout.split()[1] == "False" and int(out.stdout.split()[0]) > 100, out.stderr
