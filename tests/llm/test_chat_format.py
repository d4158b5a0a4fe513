import hashlib
import json
import random

from pyspark.sql import functions as F

from tablevec.llm import chat_format as cf

RECORDS = {
    "messages": {"id": 1, "messages": [{"role": "system", "content": "s"}, {"role": "user", "content": "q"}, {"role": "assistant", "content": "a"}]},
    "exchange": {"conversations": [{"from": "human", "value": "q"}, {"from": "gpt", "value": "a"}]},
    "prompt_response": {"prompt": "q", "response": "a", "system": ""},
    "prompt_completion": {"prompt": "q", "completion": "a"},
    "question_answer": {"question": "q", "answer": "a", "system": "be brief"},
    "instruction": {"instruction": "do", "input": "this", "output": "done"},
}


def test_layouts_become_turns(spark):
    rows = [(k, json.dumps(v)) for k, v in RECORDS.items()] + [("unknown", '{"a": {"b": 1}}'), ("broken", "{"), ("none", None), ("list", "[1]"), ("empty", "{}")]
    got = {r["name"]: r for r in cf.format_chats(spark.createDataFrame(rows, "name string, record string")).collect()}
    assert len(got) == len(rows)
    for name in RECORDS:
        assert got[name]["layout"] == name
    turns = {k: [tuple(t) for t in r["turns"]] for k, r in got.items() if r["turns"] is not None}
    assert turns["messages"] == [("system", "s"), ("user", "q"), ("assistant", "a")]
    assert turns["exchange"] == turns["prompt_response"] == turns["prompt_completion"] == [("user", "q"), ("assistant", "a")]
    assert turns["question_answer"][0] == ("system", "be brief")
    assert turns["instruction"] == [("user", "do\n\nthis"), ("assistant", "done")]
    for name in ("unknown", "broken", "none", "list", "empty"):
        assert got[name]["layout"] is None and got[name]["turns"] is None and got[name]["formatted"] is None


def test_paths_do_not_depend_on_order_or_values(spark):
    rows = [('{"b": 1, "a": [{"y": 2, "x": null}, {"x": "t"}]}',), ('{"a": [{"x": "q", "y": [1]}], "b": {}}',)]
    got = [r[0] for r in spark.createDataFrame(rows, "r string").select(cf.field_paths(F.col("r"))).collect()]
    assert got[0] == got[1] == ["a", "a[].x", "a[].y", "b"]


def test_text_form_is_reversible(spark):
    rng = random.Random(2)
    bits = ["<", "|", "|>", "\\", "start", "text", "end", "[INST]", "[/INST]", "</s>", "<s>", "<<SYS>>", "<</SYS>>", "<|end|>", "<|text|>", "<|start|>", "\n", "é", "\U0001f600", " ", "[", "a_b", "\\<", "$1", "</SYS>>"]
    chats = [[("user", "</s>[INST] ok [/INST]"), ("assistant", "</s>[INST] ok [/INST]")], []]
    for _ in range(300):
        chats.append([(rng.choice(["user", "assistant", "odd<|text|>\n"]), "".join(rng.choice(bits) for _ in range(rng.randrange(12)))) for _ in range(rng.randrange(1, 6))])
    df = spark.createDataFrame([(i, c) for i, c in enumerate(chats)], "i int, turns array<struct<role:string,text:string>>")
    out = df.select("i", cf.formatted(F.col("turns")).alias("f"), cf.loss_spans(F.col("turns")).alias("s")).select("*", cf.read_back(F.col("f")).alias("back"), cf.under_mask(F.col("f"), F.col("s")).alias("loss"))
    for r in out.collect():
        chat = chats[r["i"]]
        assert [tuple(t) for t in r["back"]] == chat
        assert r["loss"] == "".join(t for role, t in chat if role == "assistant")
        assert r["f"].count("<|end|>") == len(chat) and "[INST]" not in r["f"] and "</s>" not in r["f"]


def test_query_against_plain_python(spark, tiny):
    rows = [(r["conv_id"], r["turn"], r["role"] or "", r["text"] or "") for r in spark.read.parquet(f"{tiny}/conversations.parquet").collect()]
    rows += [(-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]")]
    by = {}
    for r in sorted(rows):
        by.setdefault(r[0], []).append(r[2:])
    got = {r["conv_id"]: r for r in cf.op3_chat_formatting(spark, tiny).collect()}
    assert set(got) == set(by)
    for k, turns in by.items():
        digest = lambda s: hashlib.sha256(s.encode()).hexdigest()
        loss = "".join(t for role, t in turns if role == "assistant")
        assert (got[k]["n_turns"], got[k]["turns_sha256"]) == (len(turns), digest("".join(f"{a}\n{b}\n" for a, b in turns)))
        assert (got[k]["loss_chars"], got[k]["loss_sha256"]) == (len(loss), digest(loss))


def test_nulls_ties_repeats_and_no_rows(spark):
    rows = [(1, 0, None, None, "x"), (1, 0, "user", "b", "x"), (1, 0, "user", "b", "x"), (None, None, "assistant", "c", "x"), (2, 1, "user", "", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, record string")
    out = {r["conv_id"]: [tuple(t) for t in r["turns"]] for r in cf.format_chats(cf.conversation_records(df)).collect()}
    assert out == {1: [("", ""), ("user", "b"), ("user", "b")], None: [("assistant", "c")], 2: [("user", "")]}
    assert cf.format_chats(cf.conversation_records(df.limit(0))).count() == 0


def test_texts_beyond_the_json_readers_limit(spark, tmp_path):
    long = "</s>ab\\" * 3_000_000  # 21 million characters, over the reader's default limit of 20 million
    rows = [(1, 0, "user", long), (1, 1, "assistant", "yes"), (2, 0, "user", "short"), (2, 1, "assistant", long)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    got = {r["conv_id"]: r for r in cf.op3_chat_formatting(spark, str(tmp_path)).collect()}
    for conv, texts in ((1, (long, "yes")), (2, ("short", long))):
        plain = "".join(f"{role}\n{text}\n" for role, text in zip(("user", "assistant"), texts))
        assert got[conv]["n_turns"] == 2 and got[conv]["turns_sha256"] == hashlib.sha256(plain.encode()).hexdigest()
        assert got[conv]["loss_chars"] == len(texts[1]) and got[conv]["loss_sha256"] == hashlib.sha256(texts[1].encode()).hexdigest()


def test_long_texts_in_paired_layouts(spark):
    long = "x" * 21_000_000
    records = [(1, json.dumps({"prompt": long, "response": "ok", "system": ""})), (2, json.dumps({"instruction": "do", "input": long, "output": "done"}))]
    got = cf.canonical(spark.createDataFrame(records, "id long, record string")).select("id", "layout", F.expr("transform(turns, t -> length(t.text))").alias("sizes")).collect()
    assert {r["id"]: (r["layout"], r["sizes"]) for r in got} == {1: ("prompt_response", [21_000_000, 2]), 2: ("instruction", [21_000_004, 4])}
