"""Findings of reviews: each test fails on the code before its fix."""

import duckdb

from avcurate.queries import ORACLES, QUERIES
from compare import same


def twin_over(spark, folder, name, **tables):
    """The query against its twin over Parquet files made from SQL."""
    con = duckdb.connect()
    for table, sql in tables.items():
        con.execute(f"COPY ({sql}) TO '{folder}/{table}.parquet' (FORMAT parquet)")
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet'")
    same(spark, con, QUERIES[name], ORACLES[name], str(folder))


def test_logarithms_of_zero(spark, tmp_path):
    twin_over(spark, tmp_path, "o_math", events="SELECT i AS event_id, TIMESTAMP '2024-01-01' AS ts, i AS user_id, 'click' AS event_type, i * 0.5::DOUBLE AS value, '{\"k\": 1}' AS props FROM range(0, 5) t(i)")


def test_sql_functions_measure_utterances(spark):
    """Their distances are sums over utterances, as those of the column expressions."""
    from avcurate.functions import sql
    from avcurate.functions.text import BREAK, asr_confidence, cer

    sql.register(spark)
    rows = [(BREAK.join(h), BREAK.join(r)) for h, r in ((["ab", "cd"], ["b", "cdd"]), (["abcd"], ["", "abcd"]), (["x" * 20, ""], ["yx1ez", "a"]), ([""], [""]), (["a", "b"], ["", ""]), (["", "Abcdefghijkl"], ["", "bcdefghijklM"]))]
    df = spark.createDataFrame(rows, "hyp string, ref string")
    df.createOrReplaceTempView("sql_utterances")
    got = spark.sql("SELECT cer(hyp, ref), asr_confidence(hyp, ref) FROM sql_utterances").collect()
    assert got == df.select(cer("hyp", "ref"), asr_confidence("hyp", "ref")).collect()
    assert [r[0] for r in got][:2] == [2 / 4, 8 / 4]


def mixed_pairs(seed):
    """Transcripts of several utterances around the sizes of words, some unanswered."""
    import random

    from avcurate.functions.text import BREAK

    rng, out = random.Random(seed), []
    for _ in range(120):
        letters, both = rng.choice(["ab", "abc é", "abcdefgh\U0001f600"]), ([], [])
        for _ in range(rng.randint(1, 3)):
            r = rng.choices(letters, k=rng.choice([0, 1, 5, 63, 64, 65, 127, 128, 129, 200]))
            h = [rng.choice([c, c, c, "", "a", c + "b"]) for c in r] if rng.random() < 0.8 else r[::-1]
            both[0].append("".join(h))
            both[1].append("".join(r))
        if rng.random() < 0.3:
            both[rng.randint(0, 1)].append("more")
        out.append(tuple(map(BREAK.join, both)))
    return out


def test_many_edits_at_once():
    """Distances, operations and their order are those of one alignment after the other."""
    from avcurate.functions import edits
    from avcurate.functions.udfs import align, answers

    hyps, refs = zip(*mixed_pairs(1))
    want = []
    for h, r in zip(hyps, refs):
        ops, at = [], [0, 0]
        for a, b in answers(h, r):
            ops += [(op, at[0] + i, at[1] + j) for op, i, j in align(a, b)]
            at = [at[0] + len(a), at[1] + len(b)]
        want.append(ops)
    names = ["hit", "sub", "del", "ins"]
    assert [list(c) for c in edits.operation_counts(hyps, refs)] == [[sum(o == n for o, _, _ in ops) for n in names] for ops in want]
    assert list(edits.distances(hyps, refs)) == [sum(o != "hit" for o, _, _ in ops) for ops in want]
    got = [[] for _ in want]
    for row, at, op, i, j in edits.operation_rows(hyps, refs):
        for a, b, c, e, f in zip(row, at, op, i, j):
            assert b == len(got[a])
            got[a].append((names[c], e, f))
    assert got == want


def test_columns_of_edits(spark):
    """Nulls stay null, word rates count words, and a pair without operations keeps its row."""
    from pyspark.sql import functions as F

    from avcurate.functions import udfs
    from avcurate.functions.text import distance

    rows = [(i, h, r) for i, (h, r) in enumerate(mixed_pairs(2))] + [(1000, None, "a"), (1001, "a", None), (1002, "", ""), (1003, "a b", " "), (1004, "a c b\x1eab", "a b\x1eab c"), (1005, "x", "")]
    df = spark.createDataFrame(rows, "pair_id long, hyp string, ref string")
    got = df.select("pair_id", udfs.edit_distance("hyp", "ref").alias("d"), distance("hyp", "ref").alias("want"), udfs.edit_ops("hyp", "ref").alias("o"), udfs.wer("hyp", "ref").alias("w")).collect()
    assert all(r.d == r.want for r in got)
    by = {r.pair_id: r for r in got}
    assert [by[i].w for i in range(1000, 1006)] == [None, None, 0.0, None, 0.5, None] and tuple(by[1000].o) == (None,) * 4
    df.createOrReplaceTempView("finding_pairs")
    spark.udtf.register("alignment_rows", udfs.AlignmentRows)
    n = {r.pair_id: r.n for r in spark.sql("SELECT pair_id, count_if(op <> 'hit') AS n FROM alignment_rows(TABLE(finding_pairs)) GROUP BY pair_id").collect()}
    assert len(n) == len(rows) and n[1002] == 0 and all(n[r.pair_id] == r.d for r in got if r.d is not None)


def test_pairs_are_measured_once(spark):
    """One evaluation of distances in the plans of the board's queries, and no text of a pair in the distinct board's shuffles."""
    from compare import SMALL

    for name in ("w5_cer", "w5_leaderboard", "w5_leaderboard_distinct"):
        plan = QUERIES[name](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("edit_distance(") == 1, name
    assert "hyp" not in [line for line in plan.splitlines() if "Join Inner" in line][0]


def test_distinct_board_keeps_null_and_equal_texts(spark):
    from avcurate.operators import baselines, evaluate

    refs = spark.createDataFrame([(1, "The end"), (2, "The end"), (3, None), (4, ""), (5, "other")], "clip_id long, ref_text string")
    columns = ["system_id", "pair_id", "dist", "ref_len", "cer", "sim"]
    want = evaluate.measured(baselines.transcribe(refs)).select(columns)
    got = evaluate.measured_once(refs, baselines.transcribe).select(columns)
    assert sorted(got.collect(), key=repr) == sorted(want.collect(), key=repr) and got.count() == 65


G_TABLES = {n: "lineitem" for n in ("g_curriculum_delta", "g_family", "g_frontier", "g_generic_delta", "g_params_frontier", "g_size_delta", "g_tab1_cs", "g_tab2_cs", "g_video_ablation", "o_map", "o_pivot")} | {"g_dataset_counts": "orders"}


def test_boards_read_a_given_table(spark):
    from compare import SMALL

    for name, table in G_TABLES.items():
        assert any(f"/{table}.parquet" in f for f in QUERIES[name](spark, SMALL).inputFiles()), name


def test_stateful_stream_ends(spark, monkeypatch):
    """A run over what is there stops after its rows."""
    from avcurate.streaming import online
    from compare import SMALL

    def run(stream):
        q = stream.writeStream.format("memory").queryName("finding_interp").option("checkpointLocation", online.shared_path(spark, "stream")).trigger(availableNow=True).start()
        try:
            assert q.awaitTermination(60)
        finally:
            q.stop()
        return spark.table("finding_interp")

    monkeypatch.setattr(online, "run_to_parquet", run)
    assert QUERIES["s_stateful_interp"](spark, SMALL).count() == spark.read.parquet(f"{SMALL}/embeddings.parquet").count()


def test_schedules_share_their_passes(spark, monkeypatch):
    """One pass for each step of all schedules together, with the weights that each gets alone."""
    import numpy as np
    from avcurate.operators import curriculum, trainer
    from avcurate.sources import fixtures as fx
    from compare import SMALL

    df = curriculum.rank_difficulty(trainer.with_quality(fx.trainable(spark, SMALL)), "quality", buckets=3, key="vec_id").where("part = 'train'").cache()
    fit = {"easy_epochs": 1, "hard_epochs": 2, "steps": 1}
    passes, gradients = [], trainer.gradients
    monkeypatch.setattr(trainer, "gradients", lambda rows, ws: passes.append(len(ws)) or gradients(rows, ws))
    together = trainer.fit_schedules(df, trainer.ALL_MODES, **fit)
    assert passes == [6, 6, 6]
    for mode in trainer.ALL_MODES:
        w, history = trainer.fit_curriculum(df, mode, **fit)
        assert np.abs(together[mode][0] - w).max() < 1e-12 and [h[:2] for h in together[mode][1]] == [h[:2] for h in history]
    assert not np.array_equal(together["two_phase"][0], together["none"][0])


def test_schedule_without_rows(spark):
    """A phase without rows changes nothing and has no loss."""
    from avcurate.operators import trainer

    df = spark.createDataFrame([([1.0, 0.0], 0, None, "train"), ([0.0, 1.0], 1, "accept", "train")], "vec array<double>, y int, split string, part string")
    fits = trainer.fit_schedules(df, ("two_phase", "none"), classes=2, dims=2, easy_epochs=1, hard_epochs=1, steps=2)
    assert [h[:2] for h in fits["two_phase"][1]] == [(1, 1), (2, 1)] and fits["two_phase"][1][1][2] is None and fits["two_phase"][0].any()
    assert len(trainer.compare_schedules(df, ("two_phase", "none"), classes=2, dims=2, steps=1).collect()) == 4


def test_letters_and_distances_of_pairs_go_to_python_once(spark):
    """Letters counted there are those of ``letter_vector``; no table of distances is filled in Catalyst."""
    from avcurate.functions.text import letter_vector
    from avcurate.functions.udfs import letter_counts
    from compare import SMALL

    texts = [None, "", "The End, the end", "\u0130I\u212aK\u017f\u1e9e\u212b", "z\x1eZ\U0001f600\u00e9", "\u0130\u0130 \u212a"]
    df = spark.createDataFrame([(t,) for t in texts], "t string")
    assert [r[0] for r in df.select(letter_counts("t")).collect()] == [r[0] for r in df.select(letter_vector("t")).collect()]
    for name in ("w5_leaderboard", "w5_leaderboard_distinct", "o_sqlfunc"):
        plan = QUERIES[name](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("letter_counts(") == 2 and plan.count("edit_distance(") + plan.count("transcript_edits(") == 1 and "levenshtein" not in plan, name


def test_distinct_board_deals_texts_once(spark):
    """Texts meet by their keys straight from the scan; nothing is dealt before that."""
    from compare import SMALL

    plan = QUERIES["w5_leaderboard_distinct"](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Repartition") == 1


def test_frontier_makes_its_board_once(spark):
    """Texts are transcribed and measured once for the board and for what dominates its rows."""
    from compare import SMALL

    for name in ("w5_frontier", "w5_params_frontier"):
        plan = QUERIES[name](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("letter_counts(") == 2 and plan.count("edit_distance(") == 1, name
        assert plan.count("ArrowEvalPython") == 2, name  # letters of references; letters and distances of hypotheses


def test_places_of_codes_by_table_and_by_comparison(monkeypatch):
    """Both ways to find where a pattern holds a code give the same distances and operations."""
    from avcurate.functions import edits

    hyps, refs = zip(*mixed_pairs(5))
    found = []
    for most in (0, edits.TABLE_WORDS):
        monkeypatch.setattr(edits, "TABLE_WORDS", most)
        found.append((edits.distances(list(hyps), list(refs)).tolist(), edits.operation_counts(list(hyps), list(refs)).tolist()))
    assert found[0] == found[1]


def test_frontier_of_ties_and_unknown_rates(spark):
    """Equals stay together; a system without a rate beats none and is beaten by none, as in the SQL."""
    from avcurate.operators import evaluate

    rows = [("a", 0.1, 0.9), ("b", 0.1, 0.9), ("c", 0.1, 0.8), ("d", 0.05, 0.2), ("e", None, 1.0), ("f", 0.3, 0.9 + 1e-12)]
    board = spark.createDataFrame(rows, "system_id string, cer double, emb_sim double")
    assert {r.system_id: r.on_frontier for r in evaluate.cs_plane(board).collect()} == {"a": True, "b": True, "c": False, "d": True, "e": True, "f": False}
