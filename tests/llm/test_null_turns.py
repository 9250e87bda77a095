"""Rows without a turn number stay in op9."""

from balcut.llm import chat


def test_null_turns_stay_and_come_last(spark, tmp_path):
    rows = [(1, 1, "assistant", "b"), (1, None, "user", "z"), (1, None, "assistant", "y"), (1, 0, "user", "a"), (2, None, "user", "q"), (2, None, None, None)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    got = {r["conv_id"]: r for r in chat.op9_chat_format(spark, str(tmp_path)).collect()}
    assert {k: r["n_turns"] for k, r in got.items()} == {1: 4, 2: 2, chat.TRAP_ID: 2}
    assert got[1]["loss_chars"] == 2
    packed = chat.canonical_turns(chat.packed_rows(spark.createDataFrame(rows[:4], "conv_id long, turn long, role string, text string")), "record", "conv_id")
    turns = packed.selectExpr("conv_id", "_fence", "inline(turns)")
    back = chat.read_back(chat.formatted(turns)).first()
    assert [t["text"] for t in back["turns"]] == ["a", "b", "y", "z"]
