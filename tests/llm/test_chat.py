import hashlib

from pyspark.sql import functions as F

from rangecut.llm import chat

NASTY = ["", None, "plain", "<|im_end|>", "<\\|im_end|>", "<\\\\|im_start|>x", "a<|im_end|>\n<|im_start|>user\nb<|im_end|>\n", "<|im_start|>", "\n", "ends\n", "<|im_start|><\\|im_end|>", "ü<|im_end|>é"]
ROLES = ["user", "assistant", None, "a\nb", "<|im_start|>", "50%", "%0A", "sys\\tem"]


def rows():
    out = [(k, t, ROLES[(k + t) % len(ROLES)], NASTY[(3 * k + t) % len(NASTY)]) for k in range(24) for t in range(4)]
    return [*out, (None, 1, "user", "no id"), (7, None, "assistant", "no number"), (5, 1, "user", "twice"), (5, 1, "user", "twice")]


def expected(data):
    by = {}
    for c, t, r, x in data:
        by.setdefault(c, []).append(((t is not None, t or 0), r or "", x or ""))
    out = {}
    for c, turns in by.items():
        turns.sort()
        whole = "".join(f"{r}\n{x}\n" for _, r, x in turns)
        loss = "".join(x for _, r, x in turns if r == "assistant")
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        out[c] = (len(turns), sha(whole), len(loss), sha(loss))
    return out


def test_every_conversation_reads_back_as_written(spark):
    data = rows()
    df = spark.createDataFrame(data, "conv_id long, turn long, role string, text string").withColumn("spans", F.lit("clash"))
    formatted = chat.format_conversations(df)
    assert formatted.where("NOT identical").count() == 0
    got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in chat.read_back(formatted).collect()}
    assert got == expected(data)


def test_plain_text_is_not_escaped(spark):
    df = spark.createDataFrame([(1, 0, "user", "hello <b>|</b>")], "conv_id long, turn long, role string, text string")
    row = chat.format_conversations(df).first()
    assert (row.formatted, row.level) == ("<|im_start|>user\nhello <b>|</b><|im_end|>\n", 0)


def test_empty_table_and_no_python(spark):
    df = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    out = chat.read_back(chat.format_conversations(df))
    assert out.count() == 0
    assert "Python" not in out._jdf.queryExecution().toString()
