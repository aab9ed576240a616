"""Line dedup of long passages on fewer than three lines, against a plain version."""

from hybridrange.llm import line_dedup


def test_long_passages_on_one_or_two_lines(spark):
    words = lambda name, n: " ".join(f"{name}{i}" for i in range(n))
    one, half, other, short = words("a", 60), words("b", 30), words("c", 25), words("d", 49)
    rows = [(1, one), (2, f"own\n {one} \nend"), (3, one), (4, f"{half}\n{other}"), (5, f"x\n{half}\n\n{other}\ny"), (6, half), (7, short), (8, short), (9, f"{one}\n{one}"), (10, None)]
    seen, want = set(), {}
    for i, text in rows:
        lines = (text or "").split("\n")
        at = [j for j, x in enumerate(lines) if x.strip()]
        gone = set()
        for n in (1, 2, 3):
            for k in range(len(at) - n + 1):
                key = tuple(lines[j].strip() for j in at[k : k + n])
                if n == 3 or sum(len(x.split()) for x in key) >= 50:
                    if key in seen:
                        gone |= set(at[k : k + n])
                    seen.add(key)
        want[i] = ("\n".join(x for j, x in enumerate(lines) if j not in gone), len(gone))
    assert [want[i][1] for i, _ in rows] == [0, 1, 1, 0, 2, 0, 0, 0, 2, 0]
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {x.doc_id: (bytes(x.kept).decode(), x.n_removed) for x in line_dedup.dedup_lines(d).collect()} == want
