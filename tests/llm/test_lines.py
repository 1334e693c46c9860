"""Line dedup against brute force."""

import random

from linkfactor.llm import lines
from linkfactor.llm.cluster import table
from linkfactor.llm.queries_near import op1_line_dedup

MID = "/root/testdata/sf0.01"
BLANK = " \t\n\x0b\x0c\r"


def plain_dedup(rows):
    """Texts after dropping all but the first (by key and number) line of each component."""
    at, sets = {}, {}
    for k, t in rows:
        for n, line in enumerate((t or "").split("\n")):
            if line.strip(BLANK):
                at.setdefault(line, set()).add((k is not None, k or 0, n))
                sets[line] = {line[i : i + lines.SHINGLE] for i in range(max(1, len(line) - lines.SHINGLE + 1))}
    root = {x: x for x in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    holders, common = {}, {}
    for x, s in sets.items():
        for g in s:
            holders.setdefault(g, []).append(x)
    for near in holders.values():
        for i, x in enumerate(near):
            for y in near[i + 1 :]:
                common[x, y] = common.get((x, y), 0) + 1
    for (x, y), n in common.items():
        if 100 * n >= 80 * (len(sets[x]) + len(sets[y]) - n):
            root[find(x)] = find(y)
    keeper = {}
    for x in sets:
        keeper[find(x)] = min(keeper.get(find(x), (True, 1 << 62, 0)), min(at[x]))
    out = []
    for k, t in rows:
        stay = [x for n, x in enumerate((t or "").split("\n")) if not x.strip(BLANK) or keeper[find(x)] == (k is not None, k or 0, n)]
        out.append((k, None if t is None else "\n".join(stay)))
    return sorted(out, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))


def test_op1_is_brute_force(spark):
    rows = [(r.doc_id, r.text) for r in table(spark, MID, "documents").collect()]
    got = op1_line_dedup(spark, MID).collect()
    want = dict(plain_dedup(rows))
    other = [r.doc_id for r in got if r.text != want[r.doc_id]]
    assert len(got) == len(rows)
    assert len(other) <= 2, other  # bands miss a link of just the wanted similarity once in fifty
    before = dict(rows)
    assert all(r.lines_lost == before[r.doc_id].count("\n") + 1 - (r.text.count("\n") + 1 if r.text or not r.lines_lost else 0) for r in got if r.text)


def test_lines_of_odd_rows(spark):
    rng = random.Random(6)
    base = "".join(rng.choice("abcdefghij klmnop") for _ in range(300))
    rows = [(1, None), (2, ""), (3, " \n\t\n"), (4, "x\nx\nÄ\nx"), (5, "x"), (6, base), (7, base[:150] + "é" + base[150:] + "\ntail\n\n"), (8, "tail"), (8, "tail"), (9, "漢\n" + base[5:]), (None, "only null\nx"), (10, "only null"), (11, "y" * 50000)]
    docs = spark.createDataFrame([(*r, 7, "z") for r in rows], "doc_id long, text string, n_chars int, lost string")
    got = lines.dedup_lines(docs)
    assert got.columns == [*docs.columns, "lines_lost"]
    found = sorted([(r.doc_id, r.text) for r in got.collect()], key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    assert found == plain_dedup(rows)
    assert all(r.n_chars == (len(r.text) if r.lines_lost else 7) for r in got.collect())
    assert lines.dedup_lines(docs.limit(0)).count() == 0


def test_cells_of_any_size_find_the_same(spark, monkeypatch):
    rng = random.Random(9)
    base = [rng.choice("abcdefgh ") for _ in range(400)]
    rows = []
    for k in range(60):  # copies that are near some others only
        text = list(base)
        for _ in range(rng.randrange(1, 9)):
            text[rng.randrange(400)] = rng.choice("xyz")
        rows.append((k, "".join(text)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = plain_dedup(rows)
    for cell in (1500, 7):
        monkeypatch.setattr("linkfactor.llm.near.CELL", cell)
        got = sorted((r.doc_id, r.text) for r in lines.dedup_lines(docs).collect())
        assert sum(a != b for a, b in zip(got, want, strict=True)) <= 2


def test_repetitive_lines_meet_whatever_their_length(spark):
    rng = random.Random(11)
    part = "".join(rng.choice("abcdefghij klmnop") for _ in range(130))
    row = "".join(rng.choice("|+ =x") for _ in range(40))
    texts = ["-" * 100, "-" * 200, "-" * 5000, "ha " * 30, "ha " * 200, row * 3, row * 9, part, part + part[:70], "other line"]
    rows = list(enumerate(texts))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id, r.text) for r in lines.dedup_lines(docs).collect())
    assert got == plain_dedup(rows)
    assert [k for k, t in got if t] == [0, 3, 5, 7, 9]
