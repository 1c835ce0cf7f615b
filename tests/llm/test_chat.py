import itertools

import numpy as np
from adaptivejoin.llm import chat


def sequential(model, rows):
    """{(conv, turn): role} by one Viterbi over each transcript."""
    out, convs = {}, {}
    for c, t, x in rows:
        convs.setdefault(c, []).append((t, x))
    for c, blocks in convs.items():
        blocks.sort(key=lambda b: (b[0], b[1] or ""))
        emits = np.array([model.emit(x or "", i == 0) for i, (_, x) in enumerate(blocks)])
        for (t, _), s in zip(blocks, chat.decode(emits, model.step), strict=True):
            out[c, t] = model.roles[s]
    return out


def test_features_and_markers():
    for text, role in (("User: hi", "user"), ("### Assistant:\nhi", "assistant"), ("[SYSTEM]: be kind", "system"), ("Q: why?", "user"), ("A: so", "assistant")):
        assert f"marker={role}" in chat.features(text, False)
        assert ":" not in chat.strip_marker(text)
    assert "marker=" in chat.features("A cat: no marker at all", False)
    assert chat.render("user", "hi") == "<|user|>\nhi\n<|end|>\n"


def test_pieces_equal_one_sequential_run(spark, sf_dir):
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    model = chat.train(turns)
    rows = [(r.conv_id, r.turn, r.text) for r in turns.collect()]
    rows += [(10_000, i, rows[i % len(rows)][2]) for i in range(900)] + [(10_001, 0, None), (10_002, 0, "User: x"), (10_002, 1, "")]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "conv_id long, turn long, text string, rendered string")
    spark.conf.set("spark.sql.shuffle.partitions", "9")
    try:
        got = {(r.conv_id, r.turn): r.role for r in chat.parse(df, model).collect()}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert got == sequential(model, rows)


def test_query_recovers_roles(spark, sf_dir):
    folder = sf_dir.replace("0.001", "0.01")
    truth = {(r.conv_id, r.turn): r.role for r in spark.read.parquet(f"{folder}/conversations.parquet").collect()}
    got = {(r.conv_id, r.turn): r.role for r in chat.query(spark, folder).collect()}
    assert got.keys() == truth.keys()
    assert sum(got[k] == truth[k] for k in truth) / len(truth) > 0.85


def test_empty_and_unlabelled(spark):
    df = spark.createDataFrame([(None, None, "x", None), (1, 0, None, None)], "conv_id long, turn long, text string, role string")
    model = chat.train(df)
    assert model.roles == ["user"]
    assert {(r.conv_id, r.role) for r in chat.parse(df, model).collect()} == {(None, "user"), (1, "user")}
    assert chat.parse(df.limit(0), model).collect() == []


def test_viterbi_equals_enumeration():
    """The best of all state sequences, ties to the states that sort first from the end backwards; with what came before, and in
    pieces chained by their transfer matrices."""
    rng = np.random.default_rng(2)
    for n, k in ((1, 3), (2, 2), (4, 3), (5, 2)):
        for rounding in (None, 0):  # rounded scores tie
            emits, step, before = rng.normal(size=(n, k)), rng.normal(size=(k, k)), rng.normal(size=k)
            if rounding is not None:
                emits, step, before = emits.round(), step.round(), before.round()
            score = lambda y: sum(emits[i, y[i]] for i in range(n)) + sum(step[y[i], y[i + 1]] for i in range(n - 1))
            every = list(itertools.product(range(k), repeat=n))
            top = max(map(score, every))
            assert chat.decode(emits, step) == list(min((y for y in every if np.isclose(score(y), top)), key=lambda y: y[::-1]))
            led = lambda y: score(y) + max(before + step[:, y[0]])
            top = max(map(led, every))
            assert np.isclose(led(chat.decode(emits, step, before)), top)
            assert np.isclose((before[:, None] + chat.transfer(emits, step, False)).max(), top)


def test_raw_transcripts_are_cut_into_turns(spark, sf_dir):
    """Labelled conversations written as one text, with markers of several kinds: roles and bodies come back."""
    turns = spark.read.parquet(f"{sf_dir.replace('0.001', '0.01')}/conversations.parquet")
    model = chat.train(turns)
    convs = {}
    for r in sorted(turns.collect(), key=lambda r: (r.conv_id, r.turn)):
        convs.setdefault(r.conv_id, []).append((r.role, (r.text or "").strip()))
    styles = ({"user": "User: ", "assistant": "Assistant: ", "system": "System: "}, {"user": "### Human:\n", "assistant": "### Bot:\n", "system": "### Instructions:\n"}, {"user": "Q: ", "assistant": "A: ", "system": "Context: "})
    rows = [(c, "\n".join(styles[c % 3].get(role, f"{role}: ") + body for role, body in ts), "clash") for c, ts in convs.items()]
    df = spark.createDataFrame(rows, "conv_id long, text string, turns string")
    right = total = 0
    for r in chat.parse_transcripts(df, model).collect():
        got, want = [(t.role, t.text) for t in r.turns], convs[r.row.conv_id]
        assert r.rendered == "".join(chat.render(*t) for t in got) and r.row.turns == "clash"
        total += len(want)
        right += sum(a == b for a, b in zip(got, want, strict=False)) if len(got) == len(want) else 0
    assert right / total > 0.9


def test_transcripts_null_blank_repeated_and_long(spark):
    model = chat.train(spark.createDataFrame([(1, 0, "hi?", "user"), (1, 1, "yes.\nit is", "assistant")], "conv_id long, turn long, text string, role string"))
    long = "User: " + "so\n" * 20_000 + "Assistant: no"
    rows = [(1, None), (2, ""), (3, " \n \n"), (4, "User: a\nAssistant: b\nc"), (4, "User: a\nAssistant: b\nc"), (None, long)]
    got = chat.parse_transcripts(spark.createDataFrame(rows, "conv_id long, text string"), model).collect()
    by = {}
    for r in got:
        by.setdefault(r.row.conv_id, []).append([(t.role, t.text) for t in r.turns])
    assert by[1] == by[2] == by[3] == [[]]
    assert by[4] == [[("user", "a"), ("assistant", "b\nc")]] * 2
    assert len(by[None][0]) == 2 and by[None][0][1] == ("assistant", "no")
    assert chat.parse_transcripts(spark.createDataFrame(rows, "conv_id long, text string").limit(0), model).collect() == []


def test_repeated_rows_long_texts_and_late_first_turns(spark):
    """Rows that repeat a place are blocks of their own; numbering may begin anywhere."""
    turns = spark.createDataFrame([(c, 7 + i, f"{'why is it so?' if i % 2 == 0 else 'it is so because it is.'}", "user" if i % 2 == 0 else "assistant") for c in range(40) for i in range(4)], "conv_id long, turn long, text string, role string")
    model = chat.train(turns)
    assert "opens=True" in model.seen
    rows = [(1, 7, "why?"), (1, 7, "why?"), (1, 8, "so " * 100_000), (2, None, "x")]
    got = chat.parse(spark.createDataFrame(rows, "conv_id long, turn long, text string"), model).collect()
    assert len(got) == 4 and {len(r.rendered) > 300_000 for r in got if r.turn == 8} == {True}
    want = sequential(model, [(c, t or 0, x) for c, t, x in rows])
    assert {(r.conv_id, r.turn or 0): r.role for r in got}.keys() == want.keys()
