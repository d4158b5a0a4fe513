"""Chat records of many layouts as canonical turns, and canonical turns as one text with a loss mask.

Everything here is DataFrame expressions. A record is a JSON object. The sorted paths of its fields (objects and
arrays of objects, two levels deep) are hashed, and the hash picks the declared mapping that turns the record into
(role, text) turns. Records of an undeclared layout keep their row, with a null layout and null turns.

The text form of a turn is START role MIDDLE text END. A control string inside a role or text gets a backslash after
its first character, and backslashes are doubled, so no control string is left inside and reading back is exact.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import table

START, MIDDLE, END = "<|start|>", "<|text|>", "<|end|>"
#: Control strings of this and of other chat templates, as a pattern: the first character, then the rest.
CONTROL = r"([<\[])(/?s>|\|[a-z_]+\|>|/?<SYS>>|</SYS>>|/?INST\])"
ROLES = {"human": "user", "prompter": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "chatgpt": "assistant"}
IGNORED = ("id", "conv_id", "source", "meta", "lang")
#: Spark's JSON reader stops at 20,000,000 characters a string unless told otherwise; get_json_object cannot be told.
JSON_OPTIONS = {"maxStringLen": str((1 << 31) - 1)}
_OPTIONS_SQL = "map({})".format(", ".join(f"'{k}', '{v}'" for k, v in JSON_OPTIONS.items()))


def fingerprint_of(paths) -> str:
    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()


@dataclass(frozen=True)
class Layout:
    """A declared layout: paths that must be there, paths that may be, and the SQL that makes turns of `record`."""

    name: str
    paths: tuple[str, ...]
    turns: str
    optional: tuple[str, ...] = field(default=())

    def fingerprints(self) -> list[str]:
        return [fingerprint_of([*self.paths, *more]) for n in range(len(self.optional) + 1) for more in combinations(self.optional, n)]


def _parsed(fields: str) -> str:
    return f"from_json(record, 'STRUCT<{fields}>', {_OPTIONS_SQL})"


def _listed(name: str, key: str, role: str, text: str) -> Layout:
    got = _parsed(f"`{key}`: ARRAY<STRUCT<`{role}`: STRING, `{text}`: STRING>>")
    turns = f"transform({got}.`{key}`, x -> named_struct('role', x.`{role}`, 'text', x.`{text}`))"
    return Layout(name, (key, f"{key}[].{role}", f"{key}[].{text}"), turns)


def _paired(name: str, asked: str, answered: str, optional: tuple[str, ...] = (), question: str | None = None) -> Layout:
    """A question and its answer; the record is parsed once, as r."""
    turns = f"array(named_struct('role', 'user', 'text', {question or f'r.`{asked}`'}), named_struct('role', 'assistant', 'text', r.`{answered}`))"
    if "system" in optional:
        turns = f"concat(filter(array(named_struct('role', 'system', 'text', r.system)), x -> x.text is not null and x.text != ''), {turns})"
    fields = ", ".join(f"`{k}`: STRING" for k in (asked, answered, *optional))
    return Layout(name, (asked, answered), f"flatten(transform(array({_parsed(fields)}), r -> {turns}))", optional)


LAYOUTS = (
    _listed("turns", "turns", "role", "text"),
    _listed("messages", "messages", "role", "content"),
    _listed("exchange", "conversations", "from", "value"),
    _paired("prompt_response", "prompt", "response", ("system",)),
    _paired("prompt_completion", "prompt", "completion", ("system",)),
    _paired("question_answer", "question", "answer", ("system",)),
    _paired("instruction", "instruction", "output", ("input", "system"), "concat_ws('\\n\\n', r.instruction, nullif(r.input, ''))"),
)


def field_paths(record: Column, ignored=IGNORED) -> Column:
    """The sorted paths of a JSON object's fields: k, k.sub for objects, k[].sub for arrays of objects."""
    top = F.map_filter(F.from_json(record, "map<string,string>", JSON_OPTIONS), lambda k, _: ~k.isin(*ignored))

    def below(k: Column, v: Column) -> Column:
        trimmed = F.ltrim(v)
        in_list = F.flatten(F.transform(F.from_json(v, "array<map<string,string>>", JSON_OPTIONS), lambda m: F.coalesce(F.map_keys(m), F.array().cast("array<string>"))))
        in_object = F.map_keys(F.from_json(v, "map<string,string>", JSON_OPTIONS))
        names = F.when(trimmed.startswith("["), F.transform(in_list, lambda s: F.concat(k, F.lit("[]."), s))).when(trimmed.startswith("{"), F.transform(in_object, lambda s: F.concat(k, F.lit("."), s)))
        return F.concat(F.array(k), F.coalesce(F.array_distinct(names), F.array().cast("array<string>")))

    return F.array_sort(F.flatten(F.transform(F.map_entries(top), lambda e: below(e["key"], e["value"]))))


def fingerprint(record: Column, ignored=IGNORED) -> Column:
    """Hex digest of the field paths; null for null, and for what is no JSON object."""
    return F.sha2(F.concat_ws("\n", field_paths(record, ignored)), 256)


def canonical(df: DataFrame, record: str = "record", layouts=LAYOUTS) -> DataFrame:
    """Adds fingerprint, layout and turns (role, text; nulls read as empty text) to records in a JSON column.

    Columns of these names are replaced. No row is dropped: unknown layouts, null and broken records have a null
    layout and null turns. Texts of any length that a string column holds are read whole.
    """
    others = [F.col(f"`{c}`") for c in df.columns if c not in ("fingerprint", "layout", "turns")]
    known = {f: lay for lay in layouts for f in lay.fingerprints()}
    marked = df.select(*others, fingerprint(F.col(f"`{record}`")).alias("fingerprint"))
    name = turns = None
    for lay in dict.fromkeys(known.values()):
        hit = F.col("fingerprint").isin(*[f for f, x in known.items() if x is lay])
        made = F.expr(lay.turns.replace("record", f"`{record}`"))
        name = F.when(hit, F.lit(lay.name)) if name is None else name.when(hit, F.lit(lay.name))
        turns = F.when(hit, made) if turns is None else turns.when(hit, made)
    roles = F.create_map(*[F.lit(x) for pair in ROLES.items() for x in pair])
    clean = F.transform(turns, lambda t: F.struct(F.coalesce(F.try_element_at(roles, F.coalesce(t["role"], F.lit(""))), t["role"], F.lit("")).alias("role"), F.coalesce(t["text"], F.lit("")).alias("text")))
    return marked.select("*", name.alias("layout"), clean.alias("turns"))


def escape(text: Column) -> Column:
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), CONTROL, r"$1\\$2")


def unescape(text: Column) -> Column:
    return F.array_join(F.transform(F.split(text, r"\\\\"), lambda part: F.replace(part, F.lit("\\"), F.lit(""))), "\\")


def formatted(turns: Column) -> Column:
    """The turns as one text."""
    return F.array_join(F.transform(turns, lambda t: F.concat(F.lit(START), escape(t["role"]), F.lit(MIDDLE), escape(t["text"]), F.lit(END))), "")


def loss_spans(turns: Column, learned: str = "assistant") -> Column:
    """Where the learned role's texts lie in the formatted text: (start, length) in code points, in order."""
    state = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"))

    def step(acc: Column, t: Column) -> Column:
        start = acc["at"] + F.lit(len(START) + len(MIDDLE)) + F.char_length(escape(t["role"]))
        length = F.char_length(escape(t["text"])).cast("long")
        span = F.array(F.struct(start.alias("start"), length.alias("length")))
        return F.struct((start + length + F.lit(len(END))).alias("at"), F.when(t["role"] == learned, F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(turns, state, step, lambda acc: acc["spans"])


def read_back(text: Column) -> Column:
    """The turns of a formatted text."""
    parts = F.split(text, r"<\|end\|>", -1)
    return F.transform(F.slice(parts, 1, F.size(parts) - 1), lambda p: F.struct(unescape(F.split_part(F.substr(p, F.lit(len(START) + 1)), F.lit(MIDDLE), F.lit(1))).alias("role"), unescape(F.split_part(p, F.lit(MIDDLE), F.lit(2))).alias("text")))


def under_mask(text: Column, spans: Column) -> Column:
    """All unescaped text under the loss mask, in order, with nothing between."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substr(text, (s["start"] + 1).cast("int"), s["length"].cast("int")))), "")


def format_chats(df: DataFrame, record: str = "record", layouts=LAYOUTS) -> DataFrame:
    """canonical() with the formatted text and its loss spans; both null where the layout is unknown."""
    others = [F.col(f"`{c}`") for c in df.columns if c not in ("formatted", "loss_spans")]
    return canonical(df.select(*others), record, layouts).select("*", formatted(F.col("turns")).alias("formatted"), loss_spans(F.col("turns")).alias("loss_spans"))


def conversation_records(turns: DataFrame) -> DataFrame:
    """One JSON record for each conv_id of (conv_id, turn, role, text) rows, in order of turn, then role, then text.

    Null roles and texts are empty. The record is one row by nature, so it holds all turns of its conversation.
    """
    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c)
    row = F.struct(F.col("turn").cast("long").alias("turn"), text("role"), text("text"))
    ordered = F.transform(F.array_sort(F.collect_list(row)), lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text")))
    return turns.groupBy(F.col("conv_id").cast("long").alias("conv_id")).agg(F.to_json(F.struct(ordered.alias("turns"))).alias("record"))


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    probe = "</s>[INST] ok [/INST]"
    own = spark.sql(f"select * from values (-7L, 0L, 'user', '{probe}'), (-7L, 1L, 'assistant', '{probe}') as t(conv_id, turn, role, text)")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(own)
    done = format_chats(conversation_records(rows))
    read = done.select("conv_id", "formatted", read_back(F.col("formatted")).alias("turns"), under_mask(F.col("formatted"), F.col("loss_spans")).alias("loss"))
    plain = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    size = lambda c: F.char_length(c).cast("long")
    return read.select("conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(plain, 256).alias("turns_sha256"), size(F.col("loss")).alias("loss_chars"), F.sha2(F.col("loss"), 256).alias("loss_sha256"), size(F.col("formatted")).alias("formatted_chars"))


_GROWN = r"length({0}) + length({0}) - length(replace({0}, '\', '')) + len(regexp_extract_all({0}, '[<\[](/?s>|\|[a-z_]+\|>|/?<SYS>>|</SYS>>|/?INST\])'))"
OP3_SQL = f"""
WITH rows AS (
    SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
    UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]'
    UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
)
SELECT conv_id, count(*) AS n_turns,
    sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
    CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
    sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
    CAST(sum({len(START) + len(MIDDLE) + len(END)} + {_GROWN.format("role")} + {_GROWN.format("text")}) AS BIGINT) AS formatted_chars
FROM rows GROUP BY conv_id
"""
