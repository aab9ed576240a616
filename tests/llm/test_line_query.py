"""The query of line dedup against its SQL on long repeats of fewer than three lines."""

import duckdb

from hybridrange.llm import line_dedup


def test_the_query_equals_its_sql_on_long_short_runs(spark, tmp_path):
    words = lambda name, n: " ".join(f"{name}{i}" for i in range(n))
    one, half, other = words("a", 60), words("b", 30), words("c", 25)
    rows = [(1, one), (2, one), (3, f"{half}\n{other}"), (4, f"x\n{half}\n{other}"), (5, "p\nq\n\nr\ns"), (6, "o\np\nq\nr"), (7, f"{one}\n{half}\n{other}"), (8, f"{one}\n{half}\n{other}\nt"), (9, None), (10, "")]
    spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    db = duckdb.connect()
    db.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{tmp_path}/documents.parquet/*.parquet')")
    names = ["doc_id", "n_lines", "n_removed", "n_runs", "kept_sha256"]
    want = sorted(db.sql(f"SELECT {', '.join(names)} FROM ({line_dedup.SQL})").fetchall())
    got = sorted(tuple(x[c] for c in names) for x in line_dedup.op8_line_dedup(spark, str(tmp_path)).collect())
    assert [x[2] for x in want] == [0, 0, 0, 0, 0, 3, 0, 3, 0, 0]
    assert got == want
