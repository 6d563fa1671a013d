"""Secret scans over a trigram inverted index, in DataFrame operations only.

Every rule's regular expression is parsed into a Boolean query over trigrams of the lower-cased text: what any match
must hold. The index lists, for the trigrams that some rule asks for, the documents that hold them; a rule's postings
are intersected clause by clause, and only its candidates are scanned by its regular expression. A rule that needs no
trigram, such as long runs of hexadecimal digits, scans every document.

Places of matches come from the pieces between them: the text split at the matches, and the matches themselves.

Defined results: a null or empty text has no secrets; rows are judged one by one, whatever their ids; rows equal in
doc_id and text share their index entry; other columns are ignored (or kept as they are by redact()).
"""

from __future__ import annotations

from dataclasses import dataclass
from re import _parser as regex_parser

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str  # for Java and RE2 alike; matches never overlap and are taken from the left
    group: int = 0  # the group that must have `least` characters
    least: int = 0


#: The base rules in their order, then public formats of well-known credentials.
BASE = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", r"[0-9a-f]{24,}"),
)
ADDED = (
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("google", r"AIza[0-9A-Za-z_-]{35}"),
    Rule("slack", r"xox[abprs]-[0-9A-Za-z-]{10,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("pem", r"-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----"),
    Rule("url", r"://[A-Za-z0-9._~-]+:[A-Za-z0-9._~!$&*+=-]+@"),
)
RULES = BASE + ADDED
MASK = "[SECRET]"
#: More alternatives of a literal, or members of a class, are not spelt out.
MOST = 64
#: Matches of a text that are gathered at a time.
BLOCK = 256


def trigram_clauses(pattern: str) -> list[frozenset[str]]:
    """Alternatives, each a set of trigrams that a match must hold together; none: any text may match."""
    clauses: list[frozenset[str]] = [frozenset()]

    def note(strings: set[str]) -> None:
        nonlocal clauses
        wanted = {frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in strings}
        if frozenset() in wanted or len(clauses) * len(wanted) > MOST:
            return
        clauses = [c | w for c in clauses for w in wanted]

    def exact(node) -> set[str] | None:
        """All strings that the node matches, lower-cased, if they are few."""
        kind, value = str(node[0]), node[1]
        if kind == "LITERAL":
            return {chr(value).lower()}
        if kind == "IN":
            found: set[str] = set()
            for what, x in value:
                if str(what) == "LITERAL":
                    found.add(chr(x).lower())
                elif str(what) == "RANGE" and x[1] - x[0] < 8:
                    found |= {chr(c).lower() for c in range(x[0], x[1] + 1)}
                else:
                    return None
            return found if len(found) <= 8 else None
        if kind == "SUBPATTERN":
            return sequence(value[-1])
        if kind == "BRANCH":
            parts = [sequence(x) for x in value[1]]
            return None if None in parts else set().union(*parts)
        if kind == "MAX_REPEAT" and value[1] <= 2:
            one = sequence(value[2])
            if one is None:
                return None
            found = set()
            for n in range(value[0], value[1] + 1):
                words = {""}
                for _ in range(n):
                    words = {a + b for a in words for b in one}
                found |= words
            return found if len(found) <= MOST else None
        return None

    def sequence(nodes) -> set[str] | None:
        found = {""}
        for node in nodes:
            part = exact(node)
            if part is None or len(found) * len(part) > MOST:
                return None
            found = {a + b for a in found for b in part}
        return found

    run = {""}
    for node in regex_parser.parse(pattern):
        part = exact(node)
        if part is not None and len(run) * len(part) <= MOST:
            run = {a + b for a in run for b in part}
        else:
            note(run)
            run = part if part is not None and len(part) <= MOST else {""}
    note(run)
    # A clause that holds another one adds nothing.
    clauses = [c for c in set(clauses) if not any(d < c for d in clauses)]
    return sorted(clauses, key=sorted) if frozenset() not in clauses else []


def _text(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit(""))


def _keys(docs: DataFrame, id_col: str, text_col: str) -> tuple[Column, Column]:
    return F.xxhash64(F.col(id_col)).alias("k1"), F.xxhash64(_text(text_col)).alias("k2")


def trigram_index(docs: DataFrame, trigrams: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Postings (trigram, k1, k2): which texts hold which of the given trigrams."""
    low = F.lower(_text(text_col))
    held = F.filter(F.array(*[F.lit(t) for t in trigrams]), lambda t: F.contains(F.col("low"), t))
    return docs.select(*_keys(docs, id_col, text_col), low.alias("low")).select("k1", "k2", F.explode(held).alias("trigram")).select("trigram", "k1", "k2")


def candidates(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, set[str]]:
    """((k1, k2, kinds): rules whose query a text answers; kinds without mandatory trigrams, which scan every text)."""
    spark = SparkSession.getActiveSession() or docs.sparkSession
    asked, full = [], set()
    for rule in rules:
        clauses = trigram_clauses(rule.pattern)
        if not clauses:
            full.add(rule.kind)
        asked += [(rule.kind, n, t, len(c)) for n, c in enumerate(clauses) for t in sorted(c)]
    queries = spark.createDataFrame(asked, "kind string, clause int, trigram string, size int")
    postings = trigram_index(docs, sorted({t for _, _, t, _ in asked}), id_col, text_col)
    # A few rows a rule: their number is fixed by the rules.
    met = postings.distinct().join(F.broadcast(queries), "trigram").groupBy("k1", "k2", "kind", "clause").agg(F.count("*").alias("n"), F.first("size").alias("size"))
    return met.where("n = size").groupBy("k1", "k2").agg(F.collect_set("kind").alias("kinds")), full


def _matches(text: Column, rule: Rule) -> Column:
    """Array of (start, end, ok, piece before, match) of a rule's matches, in code points."""
    hits = F.regexp_extract_all(text, F.lit(rule.pattern), 0)
    judged = F.regexp_extract_all(text, F.lit(rule.pattern), rule.group) if rule.group else hits
    rows = F.arrays_zip(F.slice(F.split(text, rule.pattern, -1), 1, F.size(hits)).alias("piece"), hits.alias("hit"), judged.alias("judged"))
    none = F.expr("cast(array() as array<struct<start:int,end:int,ok:boolean>>)")

    def step(acc: Column, row: Column) -> Column:
        start = acc["at"] + F.char_length(row["piece"])
        end = start + F.char_length(row["hit"])
        one = F.struct(start.alias("start"), end.alias("end"), (F.char_length(row["judged"]) >= rule.least).alias("ok"))
        return F.struct(end.alias("at"), F.concat(acc["found"], F.array(one)).alias("found"))

    def block(acc: Column, rows: Column) -> Column:
        done = F.aggregate(rows, F.struct(acc["at"].alias("at"), none.alias("found")), step)
        return F.struct(done["at"].alias("at"), F.concat(acc["found"], F.array(done["found"])).alias("found"))

    # Appending copies an array, so matches are gathered by blocks: a text of very many takes time in proportion to them.
    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(rows) - 1) / BLOCK).cast("int")), lambda b: F.slice(rows, b * BLOCK + 1, BLOCK))
    zero = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<array<struct<start:int,end:int,ok:boolean>>>)").alias("found"))
    return F.aggregate(blocks, zero, block, lambda acc: F.filter(F.flatten(acc["found"]), lambda x: x["ok"]))


def _shown(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def _marked(docs: DataFrame, rules: tuple[Rule, ...], id_col: str, text_col: str) -> tuple[DataFrame, set[str]]:
    """docs with `kinds`, the rules each text is a candidate of, as the last column."""
    found, full = candidates(docs, rules, id_col, text_col)
    k1, k2 = _keys(docs, id_col, text_col)
    rows = docs.select(F.struct(*docs.columns).alias("row"), k1, k2)
    return rows.join(found, ["k1", "k2"], "left").select("row", F.coalesce("kinds", F.array().cast("array<string>")).alias("kinds")), full


def _spans(rules: tuple[Rule, ...], full: set[str], text: Column) -> list[Column]:
    """at_<kind>, the matches of each rule whose query the text answers."""
    none = F.expr("cast(array() as array<struct<start:int,end:int,ok:boolean>>)")
    out = []
    for rule in rules:
        asked = F.lit(True) if rule.kind in full else F.array_contains("kinds", rule.kind)
        out.append(F.when(asked & text.rlike(rule.pattern), _matches(text, rule)).otherwise(none).alias(f"at_{rule.kind}"))
    return out


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_<base kind>..., base_sha256, spans), one for each row of docs."""
    marked, full = _marked(docs, rules, id_col, text_col)
    text = F.coalesce(F.col(f"row.{text_col}").cast("string"), F.lit(""))
    found = marked.select(F.col("row"), "kinds", text.alias("text")).select(F.col(f"row.{id_col}").alias("doc_id"), *_spans(rules, full, F.col("text")))

    def listed(some: tuple[Rule, ...]) -> Column:
        def placed(r: Rule):
            return lambda x: F.struct(x["start"].alias("start"), F.lit(rules.index(r)).alias("rank"), F.lit(r.kind).alias("kind"), x["end"].alias("end"))

        return F.array_sort(F.concat(*[F.transform(f"at_{r.kind}", placed(r)) for r in some]))

    base = tuple(r for r in rules if r in BASE)
    return found.select(
        "doc_id",
        *[F.size(f"at_{r.kind}").cast("long").alias(f"n_{r.kind}") for r in base],
        F.sha2(_shown(listed(base)).cast("binary"), 256).alias("base_sha256"),
        _shown(listed(rules)).alias("spans"),
    )


def redact(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text", mask: str = MASK) -> DataFrame:
    """The rows of docs with every secret replaced by the mask; an n_chars column follows the text.

    Secrets are those of scan(), in the text as it came; of overlapping ones one mask stays.
    """
    marked, full = _marked(docs, rules, id_col, text_col)
    text = F.col(f"row.{text_col}").cast("string")
    marked = marked.select("row", *_spans(rules, full, text))
    placed = F.array_sort(F.concat(*[F.transform(f"at_{r.kind}", lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"))) for r in rules]))
    marked = marked.select("row", placed.alias("at"))

    def step(acc: Column, s: Column) -> Column:
        fresh = F.struct(s["end"].alias("last"), F.concat(acc["out"], F.array(F.substring(text, acc["last"] + 1, s["start"] - acc["last"]), F.lit(mask))).alias("out"))
        return F.when(s["start"] >= acc["last"], fresh).otherwise(F.struct(F.greatest(acc["last"], s["end"]).alias("last"), acc["out"].alias("out")))

    zero = F.struct(F.lit(0).alias("last"), F.expr("cast(array() as array<string>)").alias("out"))
    whole = F.aggregate("at", zero, step, lambda acc: F.array_join(F.concat(acc["out"], F.array(F.substring(text, acc["last"] + 1, F.char_length(text)))), ""))
    marked = marked.select("row", F.when(F.size("at") > 0, whole).otherwise(text).alias("now"))
    changed = ~F.col("now").eqNullSafe(text)
    out = []
    for field in docs.schema.fields:
        own = F.col("row").getField(field.name)
        if field.name == text_col:
            out.append(F.col("now").alias(text_col))
        elif field.name == "n_chars":
            out.append(F.when(changed, F.char_length("now").cast(field.dataType)).otherwise(own).alias("n_chars"))
        else:
            out.append(own.alias(field.name))
    return marked.select(*out)


def oracle(rules: tuple[Rule, ...] = RULES) -> str:
    """DuckDB SQL for scan() over documents, by the rules alone."""
    parts = []
    for rank, r in enumerate(rules):
        p = r.pattern.replace("'", "''")
        parts.append(
            f"SELECT doc_id, {rank} AS rank, '{r.kind}' AS kind, i, "
            f"list_sum(list_transform(pieces[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(hits[1:i-1], lambda x: length(x))), 0) AS s, length(hits[i]) AS n, length(judged[i]) >= {r.least} AS ok "
            f"FROM (SELECT doc_id, pieces, hits, judged, unnest(generate_series(1, len(hits))) AS i FROM (SELECT doc_id, string_split_regex(t, '{p}') AS pieces, regexp_extract_all(t, '{p}', 0) AS hits, regexp_extract_all(t, '{p}', {r.group}) AS judged FROM d) WHERE len(hits) > 0)"
        )
    base = [r for r in rules if r in BASE]
    shown = "string_agg(kind || ':' || CAST(CAST(s AS BIGINT) AS VARCHAR) || ':' || CAST(CAST(s + n AS BIGINT) AS VARCHAR), ',' ORDER BY s, rank)"
    return (
        "WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), m AS (" + " UNION ALL ".join(parts) + "), g AS (SELECT doc_id, "
        + ", ".join(f"count(*) FILTER (WHERE kind = '{r.kind}') AS n_{r.kind}" for r in base)
        + f", {shown} FILTER (WHERE rank < {len(base)}) AS base, {shown} AS spans FROM m WHERE ok GROUP BY doc_id) "
        + "SELECT d.doc_id, " + ", ".join(f"CAST(coalesce(n_{r.kind}, 0) AS BIGINT) AS n_{r.kind}" for r in base)
        + ", sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans FROM d LEFT JOIN g USING (doc_id)"
    )
