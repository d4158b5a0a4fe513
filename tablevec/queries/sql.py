"""SQL for the core: the same definitions in the other form, with every non-link listed and sweeps written out."""

from __future__ import annotations

from tablevec.operators.lexicon import PHRASE_COLUMNS, PHRASES_OF_NAMES
from tablevec.operators.weights import Params
from tablevec.spec import SchemaSpec

SPLIT = r"'[^\p{L}\p{N}]+'"
TERM = "array_to_string(list_filter(regexp_split_to_array(lower({0}), " + SPLIT + "), lambda t: t <> ''), ' ')"
TOKENS = "list_filter(regexp_split_to_array(lower({0}), " + SPLIT + "), lambda t: t <> '')"


def values(spec: SchemaSpec) -> str:
    return " UNION ".join(f"SELECT '{t}.{c}' AS category, {c} AS value FROM {t} WHERE {c} IS NOT NULL AND {c} <> ''" for t in spec.text for c in spec.categories(t))


def links(spec: SchemaSpec) -> str:
    parts = []

    def add(kind: str, a: list[tuple[str, str, str]], b: list[tuple[str, str, str]], source: str) -> None:
        for ca, x in a:
            for cb, y in b:
                if spec.allows(ca, cb):
                    parts.append(f"SELECT DISTINCT '{kind}:{ca}>{cb}' AS rel, '{ca}' AS src_category, {x} AS src, '{cb}' AS dst_category, {y} AS dst FROM {source} WHERE {x} <> '' AND {y} <> ''")

    if "row" in spec.kinds:
        for t in spec.text:
            named = [(f"{t}.{c}", c) for c in spec.categories(t)]
            for i in range(len(named)):
                add("row", [named[i]], named[i + 1 :], t)
    if "fk" in spec.kinds:
        for k in spec.keys:
            add("fk", [(f"{k.child}.{c}", f"a.{c}") for c in spec.categories(k.child)], [(f"{k.parent}.{c}", f"b.{c}") for c in spec.categories(k.parent)], f"{k.child} a JOIN {k.parent} b ON a.{k.child_key} = b.{k.parent_key}")
    if "nm" in spec.kinds:
        for k in spec.links:
            source = f"{k.table} t JOIN {k.left} a ON t.{k.left_key} = a.{k.left_parent_key} JOIN {k.right} b ON t.{k.right_key} = b.{k.right_parent_key}"
            add("nm", [(f"{k.left}.{c}", f"a.{c}") for c in spec.categories(k.left)], [(f"{k.right}.{c}", f"b.{c}") for c in spec.categories(k.right)], source)
    return " UNION ALL ".join(parts)


def lexicon(with_corpus: bool = False) -> str:
    """lex(term, vec_id) as the body of a chain of common table expressions."""
    phrases = " UNION ".join(f"SELECT {TERM.replace("{0}", c)} AS term FROM {t}" for t, c in PHRASE_COLUMNS)
    corpus = f"UNION ALL SELECT 2, count(*), term FROM (SELECT unnest({TOKENS.replace('{0}', 'text')}) AS term FROM documents) WHERE term NOT IN (SELECT term FROM first_terms) GROUP BY term" if with_corpus else ""
    return f"""first_terms AS (
        SELECT DISTINCT term FROM ({phrases} UNION SELECT unnest({TOKENS.replace('{0}', "p_name")}) FROM part
        UNION (SELECT DISTINCT {TERM.replace("{0}", "p_name")} AS term FROM part WHERE len({TOKENS.replace('{0}', "p_name")}) = 2 ORDER BY term LIMIT {PHRASES_OF_NAMES})) WHERE term <> ''),
    terms AS (SELECT 1 AS section, 0 AS n, term FROM first_terms {corpus}),
    lex AS (SELECT term, row_number() OVER (ORDER BY section, n DESC, term) - 1 AS vec_id FROM terms QUALIFY vec_id < (SELECT count(*) FROM embeddings)),
    vecs AS (SELECT term, unnest(range(64)) AS dim, unnest(embedding)::DOUBLE AS v FROM lex JOIN embeddings USING (vec_id))"""


def hits(phrases: bool = True) -> str:
    """hits(category, value, pos, term): the greedy walk over tokens, one place at a time."""
    if not phrases:
        return f"toks AS (SELECT category, value, {TOKENS.replace('{0}', 'value')} AS t FROM nodes), hits AS (SELECT category, value, i - 1 AS pos, t[i] AS term FROM (SELECT category, value, t, unnest(range(1, len(t) + 1)) AS i FROM toks) WHERE t[i] IN (SELECT term FROM lex))"
    return f"""toks AS (SELECT category, value, {TOKENS.replace('{0}', "value")} AS t FROM nodes),
    best AS (SELECT category, value, i, max(n) AS n FROM (SELECT category, value, t, i, unnest(range(1, 5)) AS n FROM (SELECT category, value, t, unnest(range(1, len(t) + 1)) AS i FROM toks))
        WHERE i + n - 1 <= len(t) AND array_to_string(t[i:i + n - 1], ' ') IN (SELECT term FROM lex) GROUP BY category, value, i),
    walk AS (SELECT category, value, 1 AS i, 0 AS pos, CAST(NULL AS VARCHAR) AS term, len(t) AS size, t FROM toks
        UNION ALL SELECT w.category, w.value, w.i + coalesce(b.n, 1), w.pos + CASE WHEN b.n IS NULL THEN 0 ELSE 1 END, CASE WHEN b.n IS NOT NULL THEN array_to_string(w.t[w.i:w.i + b.n - 1], ' ') END, w.size, w.t
        FROM walk w LEFT JOIN best b ON b.category = w.category AND b.value = w.value AND b.i = w.i WHERE w.i <= w.size),
    hits AS (SELECT category, value, pos - 1 AS pos, term FROM walk WHERE term IS NOT NULL)"""


def start(spec: SchemaSpec, with_corpus: bool = False, phrases: bool = True) -> str:
    """WITH nodes, raw links, lex, hits, base (id, category, value, dim, v), cent."""
    return f"""WITH RECURSIVE nodes AS (SELECT category, value, category || chr(1) || value AS id FROM ({values(spec)})),
    raw AS ({links(spec)}), {lexicon(with_corpus)}, {hits(phrases)},
    mean AS (SELECT category, value, dim, avg(v) AS v FROM hits JOIN vecs USING (term) GROUP BY category, value, dim),
    dims AS (SELECT unnest(range(64)) AS dim),
    base AS (SELECT n.id, n.category, n.value, d.dim, coalesce(m.v, 0) AS v, m.v IS NULL AS is_oov FROM nodes n CROSS JOIN dims d LEFT JOIN mean m ON m.category = n.category AND m.value = n.value AND m.dim = d.dim),
    cent AS (SELECT category, dim, avg(v) AS c FROM base GROUP BY category, dim)"""


WEIGHTS = """
    l AS (SELECT rel, false AS inv, src_category || chr(1) || src AS src, dst_category || chr(1) || dst AS dst FROM raw
        UNION ALL SELECT rel, true, dst_category || chr(1) || dst, src_category || chr(1) || src FROM raw),
    outs AS (SELECT rel, inv, src, count(*) AS o FROM l GROUP BY rel, inv, src),
    ks AS (SELECT src, count(*) AS k FROM outs GROUP BY src),
    grp AS (SELECT rel, inv, count(DISTINCT src) AS ns, count(DISTINCT dst) AS nd, count(*) AS nl FROM l GROUP BY rel, inv),
    mrs AS (SELECT rel, max(k + 1) AS mr FROM l JOIN ks USING (src) GROUP BY rel),
    pairs AS (SELECT a.rel, a.inv, a.src, b.dst FROM (SELECT DISTINCT rel, inv, src FROM l) a JOIN (SELECT DISTINCT rel, inv, dst FROM l) b USING (rel, inv)),
    nons AS (SELECT p.* FROM pairs p ANTI JOIN l USING (rel, inv, src, dst))"""


def weights(spec: SchemaSpec) -> str:
    return start(spec) + "," + WEIGHTS


def objective_coefs(p: Params) -> str:
    """own(rel, inv, src, w, r); coefs(src, dst, w) with non-links listed; den(id, den)."""
    return f"""
    own AS (SELECT o.rel, o.inv, o.src, {p.link!r} / (o.o * (k.k + 1)) AS w, {p.repel!r} / (greatest(g.ns, g.nd) * m.mr) AS r FROM outs o JOIN ks k USING (src) JOIN grp g USING (rel, inv) JOIN mrs m USING (rel)),
    signed AS (SELECT l.src, l.dst, a.w + b.w AS w FROM l JOIN own a ON a.rel = l.rel AND a.inv = l.inv AND a.src = l.src JOIN own b ON b.rel = l.rel AND b.inv = NOT l.inv AND b.src = l.dst
        UNION ALL SELECT n.src, n.dst, -(a.r + b.r) FROM nons n JOIN own a ON a.rel = n.rel AND a.inv = n.inv AND a.src = n.src JOIN own b ON b.rel = n.rel AND b.inv = NOT n.inv AND b.src = n.dst),
    coefs AS (SELECT src, dst, sum(w) AS w FROM signed GROUP BY src, dst),
    den AS (SELECT n.id, {p.base!r} + {p.column!r} / (coalesce(k.k, 0) + 1) + coalesce(sum(c.w), 0) AS den FROM nodes n LEFT JOIN ks k ON k.src = n.id LEFT JOIN coefs c ON c.src = n.id GROUP BY n.id, k.k)"""


def series_coefs(p: Params, literal: bool = False) -> str:
    per = "o.o" if literal else "g.nd"
    return f"""
    own AS (SELECT o.rel, o.inv, o.src, {p.link!r} / (o.o * (k.k + 1)) AS w, {p.repel!r} / ({per} * (k.k + 1)) AS r FROM outs o JOIN ks k USING (src) JOIN grp g USING (rel, inv)),
    coefs AS (SELECT src, dst, sum(w) AS w FROM (SELECT l.src, l.dst, a.w FROM l JOIN own a USING (rel, inv, src) UNION ALL SELECT p.src, p.dst, -a.r FROM pairs p JOIN own a USING (rel, inv, src)) GROUP BY src, dst)"""


def _constant(p: Params) -> str:
    return f"{p.base!r} * b.v + {p.column!r} / (coalesce(k.k, 0) + 1) * c.c"


def objective_sweeps(p: Params, n: int) -> str:
    out = ", x0 AS (SELECT id, dim, v FROM base)"
    for i in range(n):
        out += f""", x{i + 1} AS (SELECT b.id, b.dim, ({_constant(p)} + coalesce(s.s, 0)) / d.den AS v FROM base b JOIN cent c USING (category, dim) LEFT JOIN ks k ON k.src = b.id JOIN den d ON d.id = b.id
            LEFT JOIN (SELECT e.src, x.dim, sum(e.w * x.v) AS s FROM coefs e JOIN x{i} x ON x.id = e.dst GROUP BY e.src, x.dim) s ON s.src = b.id AND s.dim = b.dim)"""
    return out


def seidel_sweep(p: Params, blocks: list[str]) -> str:
    out, last = ", x0 AS (SELECT id, dim, v FROM base)", "x0"
    for i, block in enumerate(blocks):
        out += f""", x{i + 1} AS (SELECT b.id, b.dim, CASE WHEN b.category = '{block}' THEN ({_constant(p)} + coalesce(s.s, 0)) / d.den ELSE o.v END AS v FROM base b JOIN {last} o USING (id, dim) JOIN cent c USING (category, dim) LEFT JOIN ks k ON k.src = b.id JOIN den d ON d.id = b.id
            LEFT JOIN (SELECT e.src, x.dim, sum(e.w * x.v) AS s FROM coefs e JOIN {last} x ON x.id = e.dst GROUP BY e.src, x.dim) s ON s.src = b.id AND s.dim = b.dim)"""
        last = f"x{i + 1}"
    return out


def series_sweeps(p: Params, n: int) -> str:
    out = ", x0 AS (SELECT id, dim, v FROM base)"
    for i in range(n):
        out += f""", y{i + 1} AS (SELECT b.id, b.dim, {_constant(p)} + coalesce(s.s, 0) AS v FROM base b JOIN cent c USING (category, dim) LEFT JOIN ks k ON k.src = b.id
            LEFT JOIN (SELECT e.src, x.dim, sum(e.w * x.v) AS s FROM coefs e JOIN x{i} x ON x.id = e.dst GROUP BY e.src, x.dim) s ON s.src = b.id AND s.dim = b.dim),
            x{i + 1} AS (SELECT y.id, y.dim, CASE WHEN n.n > 0 THEN y.v / n.n ELSE 0 END AS v FROM y{i + 1} y JOIN (SELECT id, sqrt(sum(v * v)) AS n FROM y{i + 1} GROUP BY id) n USING (id))"""
    return out


def graph_sweeps(n: int, exact: bool = False) -> str:
    beta = "a.beta + b.beta" if exact else "a.beta"
    out = f""", edges AS (SELECT DISTINCT src, dst FROM l WHERE src <> dst), deg AS (SELECT src, 1.0::DOUBLE / count(*) AS beta FROM edges GROUP BY src),
        coefs AS (SELECT e.src, e.dst, {beta} AS w FROM edges e JOIN deg a ON a.src = e.src JOIN deg b ON b.src = e.dst), x0 AS (SELECT id, dim, v FROM base)"""
    for i in range(n):
        out += f""", x{i + 1} AS (SELECT b.id, b.dim, (b.v + coalesce(s.s, 0)) / (1 + coalesce(w.w, 0)) AS v FROM base b LEFT JOIN (SELECT src, sum(w) AS w FROM coefs GROUP BY src) w ON w.src = b.id
            LEFT JOIN (SELECT e.src, x.dim, sum(e.w * x.v) AS s FROM coefs e JOIN x{i} x ON x.id = e.dst GROUP BY e.src, x.dim) s ON s.src = b.id AND s.dim = b.dim)"""
    return out


def compact(x: str) -> str:
    """What a vector query returns for each value."""
    return f""" SELECT b.category, b.value, round(sqrt(sum(x.v * x.v)), 6) + 0.0 AS norm, round(sum(x.v * b.v), 6) + 0.0 AS dot_base, round(sum(CASE WHEN b.dim = 0 THEN x.v ELSE 0 END), 6) + 0.0 AS first, round(sum((b.dim + 1) * x.v), 5) + 0.0 AS ramp
        FROM {x} x JOIN base b USING (id, dim) GROUP BY b.category, b.value"""


def losses(p: Params, x: str, start_as: str = "base") -> str:
    return f"""
    , gaps AS (SELECT src, dst, sum((a.v - b.v) * (a.v - b.v)) AS gap FROM (SELECT DISTINCT src, dst FROM pairs) JOIN {x} a ON a.id = src JOIN {x} b ON b.id = dst AND b.dim = a.dim GROUP BY src, dst),
    t1 AS (SELECT sum({p.base!r} * (x.v - b.v) * (x.v - b.v)) AS base_loss, sum({p.column!r} / (coalesce(k.k, 0) + 1) * (x.v - c.c) * (x.v - c.c)) AS column_loss FROM base b JOIN {x} x USING (id, dim) JOIN cent c USING (category, dim) LEFT JOIN ks k ON k.src = b.id),
    t2 AS (SELECT sum(o.w * g.gap) AS link_loss FROM l JOIN own o USING (rel, inv, src) JOIN gaps g USING (src, dst)),
    t3 AS (SELECT coalesce(sum(o.r * g.gap), 0) AS nonlink_loss FROM nons n JOIN own o USING (rel, inv, src) JOIN gaps g USING (src, dst))
    SELECT round(base_loss, 5) + 0.0 AS base_loss, round(column_loss, 5) + 0.0 AS column_loss, round(link_loss, 5) AS link_loss, round(nonlink_loss, 5) AS nonlink_loss, round(base_loss + column_loss + link_loss - nonlink_loss, 5) AS total FROM t1, t2, t3"""
