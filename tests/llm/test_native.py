"""The operators made of DataFrame functions alone: against SQL, and odd input."""

import random
from collections import Counter

import duckdb
import pytest
from adaptivejoin.llm import licences, mixing, quality


def same_as_sql(frame, sql, folder, tables):
    con = duckdb.connect()
    for t in tables:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    want, got = con.sql(sql).df(), frame.toPandas()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns) and len(got) == len(want)
    a, b = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    for c in cols:
        assert a[c].astype(object).where(a[c].notna(), None).tolist() == b[c].astype(object).where(b[c].notna(), None).tolist(), c


@pytest.mark.parametrize("module", [licences, mixing, quality])
def test_matches_sql(spark, sf_dir, module):
    same_as_sql(module.query(spark, sf_dir), module.ORACLE, sf_dir, ["documents"])


def brute_quality(text):
    ws = (text or "").encode().split()
    ws = [w.decode() for w in ws]
    windows = [tuple(ws[i : i + 5]) for i in range(len(ws) - 4)]
    often = Counter(windows)
    covered = {i + k for i, w in enumerate(windows) if often[w] > 1 for k in range(5)}
    lines = [x for x in (text or "").split("\n") if x.encode().split()]
    return len(ws), sum(map(len, ws)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def test_quality_statistics_match_brute_force(spark):
    rng = random.Random(5)
    texts = [None, "", " \n\x0b", "a", "é " * 9, "x y z " * 5000, "#*$ |<>& %\n#*$ |<>& %\n\n"]
    for _ in range(60):
        texts.append("".join(rng.choice(["a", "b", "cc", "é", "\x85"]) + rng.choice([" ", "\n", "\t", " \r\n"]) for _ in range(rng.randint(1, 80))))
    df = spark.createDataFrame([(i, t, "k") for i, t in enumerate(texts)], "doc_id long, text string, stats string")
    for r in quality.apply_rules(df).collect():
        n, chars, symbols, dup, rep = brute_quality(texts[r.row.doc_id])
        s = r.stats
        assert (s.n_words, s.word_chars, s.n_symbols, s.n_dup_lines, s.n_repeat_words) == (n, chars, symbols, dup, rep), texts[r.row.doc_id]
        assert r.base_failed == (n < 10 or 100 * rep > 20 * n)
        assert not (r.base_failed and r.kept)
    assert quality.apply_rules(df.limit(0)).collect() == []


def test_quality_keeps_good_and_drops_bad(spark, sf_dir):
    folder = sf_dir.replace("0.001", "0.1")
    labels = spark.read.parquet(f"{folder}/labels.parquet")
    rows = quality.query(spark, folder).where("not base_failed").join(labels, "doc_id").groupBy("quality", "kept").count().collect()
    n = {(r.quality, r.kept): r["count"] for r in rows}
    assert n[1, True] / (n[1, True] + n.get((1, False), 0)) > 0.99
    assert n.get((0, False), 0) / (n.get((0, True), 0) + n.get((0, False), 0)) > 0.9


def test_mixing_targets_and_copies(spark):
    rng = random.Random(6)
    rows = [(i, "w " * rng.randint(1, 30), rng.choice(["a", "a", "a", "b", "c", None])) for i in range(3000)] + [(-1, None, "z"), (-2, "", "z"), (7, "w w", "a"), (None, "w", None)]
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, source string, target int")
    plan = mixing.plan(df).collect()
    size = Counter()
    for _, t, s in rows:
        size[s] += len((t or "").split())
    target = {r.source: r.target for r in plan}
    # water filling by iteration
    names = sorted((s for s in size if s is not None)) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    want, free, rest = {}, set(names), sum(size.values())
    while True:
        over = {s for s in free if rest * weight[s] / sum(weight[x] for x in free) >= 3 * size[s]}
        if not over:
            break
        for s in over:
            want[s] = 3 * size[s]
        free -= over
        rest -= sum(want[s] for s in over)
    for s in free:
        want[s] = rest * weight[s] / sum(weight[x] for x in free)
    assert target == pytest.approx(want)
    assert sum(target.values()) == pytest.approx(sum(size.values()))
    taken = Counter()
    for r in plan:
        taken[r.source] += r.taken
        assert r.taken <= 3 * r.size and r.taken % max(r.size, 1) == 0
    for s in names:
        assert taken[s] == pytest.approx(want[s], rel=0.1)
    assert sorted(map(str, plan)) == sorted(map(str, mixing.plan(df.repartition(5)).collect()))
    mixed = mixing.mix(df)
    assert mixed.columns == df.columns
    assert mixed.count() == sum(r.copies for r in plan)
    assert mixing.plan(df.limit(0)).collect() == [] and mixing.mix(df.limit(0)).collect() == []


def test_licences(spark):
    own = dict(reversed(licences.LICENCES))
    text = "Copyright (c) 2020 Someone\nAll rights reserved.\n\n" + own["MIT"].upper().replace("SUBLICENSE", "sub-licence")
    rows = [(1, text, "x"), (1, text, "x"), (2, None, "x"), (3, "", "x"), (4, "© 2020", "x"), (5, "a\nReleased under the MIT licence!\nb\nreleased under the mit license", "x"), (None, own["ISC"], "x"), (6, own["MIT"] + " more", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, digest string")
    got = {(r.doc_id, r.license_id, r.n_notices, r.notice_ids) for r in licences.scan(df).collect()}
    assert got == {(1, "MIT", 0, ""), (2, None, 0, ""), (3, None, 0, ""), (4, None, 0, ""), (5, None, 2, "MIT"), (None, "ISC", 0, ""), (6, None, 0, "")}
    assert licences.scan(df).count() == 8
    assert licences.scan(df.limit(0)).collect() == []
    found = sorted((r.doc_id, r.line, r.license_id) for r in licences.notices(df).collect())
    assert found == [(5, 1, "MIT"), (5, 3, "MIT")]


def test_every_known_text_and_notice_is_found(spark):
    """Rewrapped, titled, behind comment signs."""
    texts = [(i, "Copyright 2021 X\n" + t.replace(", ", ",\n"), name) for i, (name, t) in enumerate(licences.LICENCES)]
    got = {r.doc_id: r.license_id for r in licences.scan(spark.createDataFrame(texts, "doc_id long, text string, name string")).collect()}
    assert got == {i: name for i, _, name in texts}
    lines = [(i, f"x = 1\n// {t}\n", name) for i, (name, t) in enumerate(licences.NOTICES)]
    got = {r.doc_id: (r.n_notices, r.notice_ids) for r in licences.scan(spark.createDataFrame(lines, "doc_id long, text string, name string")).collect()}
    assert got == {i: (1, name) for i, _, name in lines}


def test_licences_of_rows_that_share_an_id(spark):
    """Each row keeps its own result, null ids too."""
    rows = [(1, "Released under the MIT License."), (1, "nothing here"), (None, "SPDX-License-Identifier: ISC\nSPDX-License-Identifier: MIT\nSPDX-License-Identifier: ISC"), (None, "none")]
    got = licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r.doc_id or 0, r.n_notices, r.notice_ids) for r in got) == [(0, 0, ""), (0, 3, "ISC,MIT"), (1, 0, ""), (1, 1, "MIT")]


def test_scan_is_one_pass_without_exchange(spark, sf_dir):
    plan = licences.query(spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan") == 1 and "SortMergeJoin" not in plan and "Python" not in plan


def test_mixing_of_null_ids_and_equal_rows_meets_its_target(spark):
    """A source of rows without id, and one of a single repeated row: both near their targets, whatever the partitions."""
    rows = [(None, f"{i} " * 4, "a") for i in range(1000)] + [(5, "x y z", "b")] * 1000 + [(i, "q " * 3, "c") for i in range(2000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    results = []
    for part in (df, df.repartition(7)):
        plan = mixing.plan(part).collect()
        for s in "abc":
            own = [r for r in plan if r.source == s]
            assert sum(r.taken for r in own) == pytest.approx(own[0].target, rel=0.06)
        results.append(sorted((r.source, str(r.doc_id), r.size, r.copies) for r in plan if r.source == "b"))
        assert mixing.mix(part).count() == sum(r.copies for r in plan)
    assert results[0] == results[1]
