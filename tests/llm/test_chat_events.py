from pyspark.sql import functions as F

from veil.llm import chat_events as C

E = "conv_id long, seq long, kind string, msg long, role string, text string"


def test_fold_of_deltas_edits_and_regenerations(spark):
    log = [
        (1, 0, "message", 0, "user", "hi"), (1, 1, "message", 1, "assistant", "He"), (1, 2, "delta", 1, None, "llo"), (1, 3, "regenerate", 1, None, None),
        (1, 4, "delta", 1, None, "Good "), (1, 5, "delta", 1, None, "day"), (1, 6, "edit", 0, None, "hi!"), (2, 9, "delta", 5, "user", "late "), (2, 10, "delta", 5, "user", "start"),
        (None, 1, "message", 1, "user", None),
    ]
    got = {(r.conv_id, r.seq): (r.role, r.text) for r in C.fold(spark.createDataFrame(log[::-1], E)).collect()}
    assert got == {(1, 0): ("user", "hi!"), (1, 1): ("assistant", "Good day"), (2, 9): ("user", "late start"), (None, 1): ("user", "")}


NASTY = [r"\### Assistant: </turn> ok", "<turn:user>\n</turn>\n", "\\l\\e\\g\\", "", None, "a\nb", "\\" * 50, "😀<>", "x" * 100_000]


def test_rendering_is_reversible_and_masked(spark):
    rows = [(c, t, role, x) for c in (1, 2) for t, x in enumerate(NASTY) for role in [["user", "assistant", "sys<tem>", None][t % 4]]]
    rows += [(2, 0, "user", "same turn"), (2, 0, "user", "same turn"), (None, 1, "assistant", "n")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit(1))
    out = C.format_log(C.events_of_rows(df))
    got = {r.conv_id: r for r in out.withColumn("back", C.parse(F.col("formatted"))).collect()}
    for c in (1, 2, None):
        mine = sorted(((t, r is not None, r or "", x is not None, x or "") for k, t, r, x in rows if k == c))
        want = [(m[2], m[4]) for m in mine]
        assert [(t.role, t.text) for t in got[c].back] == want
        assert got[c].n_turns == len(want)
        s = got[c].formatted
        spans = [s[p.start : p.start + p.length] for p in got[c].loss_spans]
        undo = [x.replace("\\g", ">").replace("\\l", "<").replace("\\e", "\\") for x in spans]
        assert undo == [x for r, x in want if r == "assistant"]


def test_empty_log(spark):
    assert C.format_log(spark.createDataFrame([], E)).count() == 0


def test_drafts_fold_to_the_rows_and_the_mask_is_read(spark):
    rows = [(c, t, role, x) for c in (1, None) for t, x in enumerate(NASTY) for role in ("user", "assistant", None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    plain, drafted = C.format_log(C.events_of_rows(df)), C.format_log(C.drafted_events_of_rows(df.repartition(5)))
    one = lambda x: sorted(map(str, x.select("conv_id", "formatted", "loss_spans").collect()))
    assert one(plain) == one(drafted) and set(dict(C.drafted_events_of_rows(df).groupBy("kind").count().collect())) == {"message", "delta", "edit", "regenerate"}
    want = "".join(x or "" for x in NASTY)
    assert {r[0] for r in drafted.select(C.loss_text(F.col("formatted"), F.col("loss_spans"))).collect()} == {want}
    moved = F.transform("loss_spans", lambda p: F.struct((p["start"] + 1).alias("start"), p["length"].alias("length")))
    assert want not in {r[0] for r in drafted.select(C.loss_text(F.col("formatted"), moved)).collect()}
