import hashlib

from hypothesis import given, settings
from hypothesis import strategies as st

from veilframe.llm import chat as C

PIECES = st.lists(st.sampled_from([*C.CONTROL, "\\", "<", "|", "[", "0;", "\\0;", "n", "word ", "é", "\n"]), max_size=12).map("".join)


@settings(max_examples=300, deadline=None)
@given(PIECES)
def test_escapes_are_reversible_and_hide_control(text):
    e = C.escape(text)
    assert C.unescape(e) == text and not any(c in e for c in C.CONTROL)


def brute(rows):
    turns, loss = "", ""
    for _, role, text in sorted(rows, key=lambda r: (r[0], r[1] or "", r[2] or "")):
        turns += f"{role or ''}\n{text or ''}\n"
        if role == "assistant":
            loss += text or ""
    return len(rows), hashlib.sha256(turns.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest()


def test_read_back_equals_the_table(spark, sf_mid):
    rows = spark.read.parquet(f"{sf_mid}/conversations.parquet").collect()
    by = {-1: [(0, "user", "</s>[INST] ok [/INST]"), (1, "assistant", "</s>[INST] ok [/INST]")]}
    for r in rows:
        by.setdefault(r.conv_id, []).append((r.turn, r.role, r.text))
    got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in C.op3_chat_formatting(spark, sf_mid).collect()}
    assert got == {k: brute(v) for k, v in by.items()}


def test_windows_keep_the_system_turn_and_the_budget(spark):
    rows = [(7, 0, "system", "be brief now")] + [(7, i, "user" if i % 2 else "assistant", f"turn {i} " + "w " * 10) for i in range(1, 60)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = sorted(C.format_windows(df, budget=60, history=20).collect(), key=lambda r: r.window_no)
    assert len(out) > 5 and all(r.n_tokens <= 60 and not r.over_budget for r in out)
    assert all("be brief now" in r.formatted for r in out)
    assert all(r.n_repeated == 2 for r in out[1:])  # the system turn and one turn of history
    assert sum(r.n_new for r in out) == 60
    seen = [t for r in out for _, t, _ in C.read_windows(r.formatted, r.loss_spans)]
    assert seen == [r[3] for r in rows]
    masked = [r.formatted[r.loss_spans[i] : r.loss_spans[i + 1]] for r in out for i in range(0, len(r.loss_spans), 2)]
    assert masked == [r[3] for r in rows if r[2] == "assistant"]


def test_edges(spark):
    rows = [(1, 0, None, None, "x"), (1, 0, None, None, "x"), (None, None, "assistant", "a", "x"), (None, 2, "user\nodd", "b", "x"), (2, 0, "assistant", "big " * 900, "x"), (2, 1, "user", "", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, formatted string")
    got = {r.conv_id: r for r in C.read_back(C.format_windows(df, 64, 16)).collect()}
    assert got[1].n_turns == 2 and got[None].n_turns == 2 and got[2].loss_chars == 3600 and got[2].n_windows == 2
    assert got[None].turns_sha256 == hashlib.sha256(b"assistant\na\nuser\nodd\nb\n").hexdigest()
    assert C.read_back(C.format_windows(df.where("turn > 99"))).count() == 0
