import hashlib

from querygrade.llm.chat_trees import op8_chat_formatting


def test_every_row_of_tied_and_null_turns_is_kept(spark, tmp_path):
    rows = [(1, 0, "user", "b"), (1, 0, "user", "a"), (1, 1, "assistant", "c"), (1, 1, "assistant", "c"), (1, None, "user", "last"), (2, 5, "assistant", None)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(3).write.parquet(str(tmp_path / "conversations.parquet"))
    got = {r.conv_id: r for r in op8_chat_formatting(spark, str(tmp_path)).collect()}
    said = [("user", "a"), ("user", "b"), ("assistant", "c"), ("assistant", "c"), ("user", "last")]
    assert set(got) == {-7, 1, 2} and (got[1].n_turns, got[1].loss_chars, got[2].n_turns) == (5, 2, 1)
    assert got[1].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in said).encode()).hexdigest()


def test_roles_of_any_form_and_rows_without_id(spark, tmp_path):
    rows = [(1, 0, "System Prompt", "s"), (1, 1, "Assistant", "not a loss text"), (1, 2, "a\\nb\nc:\n", "x"), (1, 3, None, None), (1, 4, "assistant", "### y"), (None, 0, "user", "n"), (None, 1, "assistant", "m")]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(3).write.parquet(str(tmp_path / "conversations.parquet"))
    got = {r.conv_id: r for r in op8_chat_formatting(spark, str(tmp_path)).collect()}
    assert set(got) == {-7, 1, None} and got[None].n_turns == 2
    assert got[1].turns_sha256 == hashlib.sha256("".join(f"{r or ''}\n{t or ''}\n" for _, _, r, t in rows[:5]).encode()).hexdigest()
    assert (got[1].loss_chars, got[1].loss_sha256) == (5, hashlib.sha256(b"### y").hexdigest())
