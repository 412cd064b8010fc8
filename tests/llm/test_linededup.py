import duckdb
import pandas as pd
import pytest

from prefpat.llm import linededup


def line(name, n):
    return " ".join(f"{name}{i}" for i in range(n))


def run(spark, rows, extra=""):
    df = spark.createDataFrame([(k, t, "keep") for k, t in rows], "doc_id long, text string, gone string")
    out = linededup.without_repeats(df, "doc_id", "text")
    assert out.columns == ["doc_id", "text", "gone"]
    return sorted(((r.doc_id, r.text) for r in out.collect()), key=str)


def test_shared_passages_go_wherever_they_stand(spark):
    passage = "\n".join([line("p", 14), line("q", 20), line("r", 9), line("s", 17)])
    alone = line("long", 60)
    rows = [
        (1, "\n".join([line("a", 12), passage, line("b", 12)])),
        (2, "\n".join([line("c", 5), line("d", 30), passage])),
        (3, "\n".join([passage, line("e", 12)])),
        (4, "\n".join([line("f", 12), alone, line("g", 12)])),
        (5, "\n".join([alone, line("h", 3)])),
        (6, "\n".join([line("i", 12), line("j", 12), line("k", 12)])),
    ]
    got = dict(run(spark, rows))
    assert got[1] == rows[0][1] and got[4] == rows[3][1] and got[6] == rows[5][1]
    assert got[5] == line("h", 3)
    assert got[2] == "\n".join([line("c", 5), line("d", 30)]) and got[3] == line("e", 12)


def texts_around(passage, n):
    """The passage in ``n`` texts, between lines that no other text has."""
    around = lambda i, side: [line(f"{side}{i}x{j}_", 3 + (i * 5 + j * 11) % 40) for j in range(1 + (i + len(side)) % 4)]
    return [(i, "\n".join([*around(i, "before"), *passage, *around(i, "behind")])) for i in range(n)]


@pytest.mark.parametrize("widths", [[2] * 30, [3] * 20, [4] * 15, [20, 20, 20], [10, 0] * 6, [20, 0] * 3, [6, 0] * 10, [60], [1] * 70, [30, 1, 30], [5, 25, 1, 1, 40]])
def test_passages_of_fifty_words_go_however_they_are_cut(spark, widths):
    """Short lines, long ones, blank lines between, and no boundary at all."""
    rows, kept, planted = [], 0, 0
    for p in range(6):
        passage = [line(f"p{p}w{j}_", n) for j, n in enumerate(widths)]
        rows += [(1000 * p + k, t.replace("before", f"b{p}").replace("behind", f"e{p}")) for k, t in texts_around(passage, 4)]
        planted += 3 * sum(widths)
    for key, text in run(spark, rows):
        if key % 1000:
            kept += sum(w.startswith("p") for w in text.split())
        else:
            assert text == dict(rows)[key]
        assert sum(w[0] in "be" for w in text.split()) == sum(w[0] in "be" for w in dict(rows)[key].split())
    assert kept <= 0.02 * planted


def test_blank_lines_do_not_tell_chunks_apart(spark):
    a, b, c = line("a", 30), line("b", 30), line("c", 9)
    got = dict(run(spark, [(1, f"{a}\n{b}\n{c}"), (2, f"{a}\n\n\n{b}\n{c}"), (3, f"x y\n{a}\n \n{b}\n\n{c}\nz")]))
    assert got[1] == f"{a}\n{b}\n{c}" and got[2] == "" and got[3].split() == ["x", "y", "z"]


def test_odd_rows(spark):
    same = "\n".join([line("m", 30), line("n", 30)])
    rows = [(None, same), (1, same), (1, same), (2, None), (3, ""), (4, "\n\n\n"), (5, "x\n" * 5000), (6, "word " * 20000), (7, same + "\n" + same)]
    got = run(spark, rows)
    assert sorted(str(t) for k, t in got if k is None) == [same]
    assert [t for k, t in got if k == 1] == ["", ""]
    assert next(len(t.split()) for k, t in got if k == 5) < 5000  # a text's own repeats go as well
    rest = dict((k, t) for k, t in got if k not in (None, 1))
    assert rest[2] is None and rest[3] == "" and rest[4] == "\n\n\n" and rest[6] == "word " * 20000 and rest[7] == ""
    assert linededup.without_repeats(spark.createDataFrame([], "doc_id long, text string"), "doc_id", "text").count() == 0


def test_sql_form_agrees(spark):
    rows = [(i, "\n".join(line(f"{(i * 7 + j) % 23}_", (i + j) % 60 if j % 3 else (i * j) % 6) for j in range(i % 25))) for i in range(120)]
    documents = pd.DataFrame(rows, columns=["doc_id", "text"])  # noqa: F841
    want = sorted((int(k), t) for k, t, *_ in duckdb.sql(f"SELECT doc_id, text FROM ({linededup.OP10_SQL})").fetchall())
    assert run(spark, rows) == sorted(want, key=str)


def test_spans_are_made_once_and_none_twice(spark):
    """Counting and joining read the same written spans; a chunk read forward and backward is one."""
    lines = [" ".join(f"w{(i * 7 + j) % 23}" for j in range(i % 9 + 3)) for i in range(120)]
    texts = ["\n".join(lines[a : a + n]) for a in range(0, 100, 5) for n in (1, 2, 3, 12)] + ["", "\n \n", " ".join(lines), None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4).cache()
    plan = linededup.repeated_spans(df, "doc_id", "text")._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan
    for r in df.where("text is not null").select(linededup.spans_of(df.text).alias("s")).collect():
        assert len(set(r.s)) == len(r.s)
