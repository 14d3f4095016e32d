"""Line dedup by a log-template tree, in DataFrame operations alone.

The tree has a fixed depth. A line's path is its number of tokens, then its ``depth`` leading tokens; tokens with a digit in them are variable
fields and stand as one wildcard everywhere. Leaves that fewer documents reach than a template needs are left at once. In a leaf, lines
meet through their generalisations: the line itself (0); of a body of at least ``min_body`` further tokens, the six that keep two
of its four quarters and let the others vary (so a template's lines agree in half of the body at least, wherever their word fields are);
of a shorter body of three tokens or more, those that let one token vary. A generalisation of enough documents is a template: ``min_docs``,
and ``long_docs`` for whole lines of ``long_tokens`` or more. A line joins the template of the most documents (ties: the
lesser number of the generalisation), and its tokens merge into it: where the joined lines differ, the template has a wildcard. Lines with
a template are dropped from all documents but the first (the least id) of each.

Defined results: a null text has one empty line and stays null; lines of fewer than ``min_tokens`` tokens are never dropped; a repeated row
(same id, same text) is the same document; null ids are ordered last; texts and lines are read whole; an empty table gives an
empty result; further columns are carried along, whatever their names. Generalisations are told apart by 64 bits of hash, documents by
these and their id: among 10^12 generalisations some tens of thousands of pairs collide, which drops a line only where the
documents of both together are enough.
"""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

DEPTH, MIN_TOKENS, MIN_BODY, MIN_DOCS = 3, 3, 8, 3
#: Whole lines of so many tokens recur from so many documents on.
LONG_TOKENS, LONG_DOCS = 50, 2
#: What a generalisation keeps of a long body's four quarters, in order of its number.
KEPT = list(itertools.combinations(range(4), 2))
WILD = "<*>"

#: A token with a digit, from its beginning on; linear in the line's length.
_FIELD = r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D0-9]*+[0-9][^\x20\x09-\x0D]*+"


def _row_key(id_col: str, text_col: str):
    return F.xxhash64(F.col(id_col), F.col(text_col), F.col(text_col).isNull())


def _tokens(line: str):
    """Column: the line's tokens, fields as wildcards."""
    masked = F.when(F.col(line).rlike("[0-9]"), F.regexp_replace(line, _FIELD, WILD)).otherwise(F.col(line))
    return masked, lambda body: F.when(
        F.col(body).rlike(r"[\x09-\x0D]|\x20\x20|^\x20|\x20\z"), F.split(F.btrim(F.col(body), F.lit(" \t\n\x0b\x0c\r")), r"[\x20\x09-\x0D]+", -1)
    ).otherwise(F.split(body, " ", -1))


def line_keys(docs: DataFrame, depth: int = DEPTH, min_tokens: int = MIN_TOKENS, min_body: int = MIN_BODY, long_tokens: int = LONG_TOKENS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """row, id, pos, leaf and the generalisations' keys of every line that has enough tokens. The lowest bit of a key tells whole long lines."""
    lines = docs.select(_row_key(id_col, text_col).alias("row"), F.col(id_col).alias("id"), F.posexplode(F.split(common.whole_text(docs, text_col), "\n", -1)).alias("pos", "line"))
    # explode(array(x)) computes x once for all that follows; plain columns would be computed anew in every filter and branch
    masked, split = _tokens("line")
    bodies = lines.where(F.length("line") > 0).select("row", "id", "pos", F.explode(F.array(masked)).alias("body"))
    cut = bodies.select("row", "id", "pos", F.explode(F.array(split("body"))).alias("tokens"))
    counted = cut.withColumn("n", F.size("tokens")).where((F.col("n") >= min_tokens) & (F.element_at("tokens", 1) != ""))
    leaf = F.xxhash64("n", F.slice("tokens", 1, depth))
    body = F.greatest(F.col("n") - depth, F.lit(0))
    at = [depth + F.floor(body * k / 4).cast("int") for k in range(5)]
    parts = [F.xxhash64(F.slice("tokens", at[k] + 1, at[k + 1] - at[k])) for k in range(4)]
    told = counted.select("row", "id", "pos", "n", "tokens", F.explode(F.array(F.struct(leaf.alias("leaf"), *[p.alias(f"q{k}") for k, p in enumerate(parts)]))).alias("h"))
    whole = F.xxhash64(F.lit(0), "h.leaf", "h.q0", "h.q1", "h.q2", "h.q3")
    whole = F.when(F.col("n") >= long_tokens, whole.bitwiseOR(F.lit(1))).otherwise(whole.bitwiseAND(F.lit(-2)))
    even = lambda c: c.bitwiseAND(F.lit(-2))
    halves = F.array(whole, *[even(F.xxhash64(F.lit(k + 1), "h.leaf", f"h.q{i}", f"h.q{j}")) for k, (i, j) in enumerate(KEPT)])
    one_less = F.transform(F.sequence(F.lit(1), F.col("n") - depth), lambda i: even(F.xxhash64(i, F.col("h.leaf"), F.slice("tokens", F.lit(depth + 1), i - 1), F.slice("tokens", i + depth + 1, F.col("n")))))
    keys = F.when(F.col("n") >= depth + min_body, halves).when(F.col("n") >= depth + 3, F.concat(F.array(whole), one_less)).otherwise(F.array(whole))
    return told.select("row", "id", "pos", "h.leaf", keys.alias("keys"))


def _documents_of(keys: DataFrame, key: str) -> DataFrame:
    """key, n_docs, first_row. Both sums combine before their shuffle."""
    each = keys.groupBy(key, "row").agg(F.min("id").alias("id"))
    order = F.struct(F.col("id").isNull().alias("late"), "id", "row")
    return each.groupBy(key).agg(F.count("*").alias("n_docs"), F.min(order).alias("first")).select(key, "n_docs", F.col("first.row").alias("first_row"))


def templates_of(docs: DataFrame, min_docs: int = MIN_DOCS, long_docs: int = LONG_DOCS, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """row, id and found: of the row's lines with a template, their place (pos), key, number (idx) and whether they are dropped."""
    keys = common.keep(line_keys(docs, id_col=id_col, text_col=text_col, **how), "lines")
    leaves = _documents_of(keys.select("leaf", "row", "id"), "leaf").where(F.col("n_docs") >= min(min_docs, long_docs)).select("leaf")
    near = keys.join(leaves, "leaf").select("row", "id", "pos", F.posexplode("keys").alias("idx", "key"))
    near = common.keep(near, "near")  # tables of their own, so that a hot key's join can be split
    least = F.when(F.col("key").bitwiseAND(F.lit(1)) == 1, long_docs).otherwise(min_docs)
    many = common.keep(_documents_of(near.select("key", "row", "id"), "key").where(F.col("n_docs") >= least), "templates")
    common.drop_scratch(docs.sparkSession, keys)
    hits = near.join(many, "key")
    best = F.max_by(F.struct("key", "idx"), F.struct("n_docs", -F.col("idx")))
    lines = hits.groupBy("row", "id", "pos").agg(best.alias("b"), F.max(F.col("row") != F.col("first_row")).alias("drop"))
    return lines.groupBy("row", "id").agg(F.array_sort(F.collect_list(F.struct("pos", "b.key", "b.idx", "drop"))).alias("found"))


def _with_found(docs: DataFrame, **how) -> tuple[DataFrame, str, str]:
    """docs with the array of templates_of, and the names of its column and of one for the lines."""
    id_col, text_col = how.get("id_col", "doc_id"), how.get("text_col", "text")
    row, key, same, found, lines = common.fresh(docs, "row", "key", "same", "found", "lines")
    told = templates_of(docs, **how).select(F.col("row").alias(key), F.col("id").alias(same), F.col("found").alias(found))
    out = docs.withColumn(row, _row_key(id_col, text_col))
    out = out.join(told, (F.col(row) == F.col(key)) & F.col(id_col).eqNullSafe(F.col(same)), "left")
    return out.withColumn(lines, F.split(text_col, "\n", -1)), found, lines


def _left(found: str, lines: str, text_col: str):
    gone = F.transform(F.filter(found, lambda x: x["drop"]), lambda x: x["pos"])
    return F.when(F.col(found).isNull(), F.col(text_col)).otherwise(F.array_join(F.filter(lines, lambda _, i: ~F.array_contains(gone, i)), "\n"))


def drop_recurring(docs: DataFrame, **how) -> DataFrame:
    """docs with the recurring lines gone from the text; how: the parameters of templates_of and line_keys."""
    out, found, lines = _with_found(docs, **how)
    text_col = how.get("text_col", "text")
    return out.withColumn(text_col, _left(found, lines, text_col)).select(*docs.columns)


def dropped_lines(docs: DataFrame, **how) -> DataFrame:
    """id, n_lines, text (what is left) of every row, and told: its lines with a template (pos, key, idx, drop, line)."""
    out, found, lines = _with_found(docs, **how)
    text_col = how.get("text_col", "text")
    told = F.transform(found, lambda x: F.struct(x["pos"].alias("pos"), x["key"].alias("key"), x["idx"].alias("idx"), x["drop"].alias("drop"), F.get(lines, x["pos"]).alias("line")))
    n = F.coalesce(F.size(lines), F.lit(1)).cast("long")
    return out.select(F.col(how.get("id_col", "doc_id")).alias("id"), F.when(F.col(text_col).isNull(), 1).otherwise(n).cast("long").alias("n_lines"), _left(found, lines, text_col).alias("text"), told.alias("told"))


def merged(lines: DataFrame) -> DataFrame:
    """key, template, n_lines: the tokens of the lines (key, line) of each template merged, wildcards where they differ."""
    masked, split = _tokens("line")
    each = lines.select("key", F.explode(F.array(masked)).alias("body")).select("key", split("body").alias("tokens"))
    # equal lines of a hot template are one row before they meet at their key
    tokens = common.keep(each.groupBy("key", "tokens").agg(F.count("*").alias("n")), "tokens")
    base = tokens.groupBy("key").agg(F.min("tokens").alias("base"), F.sum("n").alias("n_lines"))
    off = F.filter(F.transform("tokens", lambda t, i: F.when(t != F.get("base", i), i)), lambda i: i.isNotNull())
    # a table of its own, so that a hot template's join can be split
    vary = common.keep(tokens.join(base.select("key", "base"), "key").select("key", F.explode(off).alias("p")), "vary")
    vary = vary.groupBy("key").agg(F.collect_set("p").alias("vary"))
    wild = F.transform("base", lambda t, i: F.when(F.array_contains("vary", i), WILD).otherwise(t))
    return base.join(vary, "key", "left").select("key", F.array_join(F.when(F.col("vary").isNull(), F.col("base")).otherwise(wild), " ").alias("template"), "n_lines")


def op8_line_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    left = dropped_lines(common.documents(spark, sf_dir))
    kept, dropped = F.coalesce("text", F.lit("")), F.coalesce(F.size(F.filter("told", lambda x: x["drop"])), F.lit(0))
    rows = left.select(
        F.monotonically_increasing_id().alias("number"), F.col("id").alias("doc_id"), "n_lines", F.when(F.col("told").isNull(), 0).otherwise(dropped).cast("long").alias("n_dropped"),
        F.length(kept).cast("long").alias("kept_chars"), F.sha2(kept, 256).alias("kept_sha256"), "told",
    )
    rows = common.keep(rows, "told")  # digests, and the lines with a template alone
    each = rows.select("number", F.explode("told").alias("x")).select("number", "x.*")
    named = each.join(merged(each), "key").groupBy("number").agg(F.array_sort(F.collect_list(F.struct("pos", "template"))).alias("t"))
    said = F.array_join(F.transform("t", lambda x: x["template"]), "\n")
    return rows.drop("told").join(named, "number", "left").select("doc_id", "n_lines", "n_dropped", "kept_chars", "kept_sha256", F.sha2(F.coalesce(said, F.lit("")), 256).alias("templates_sha256"))


#: The same for DuckDB, from the definition: keys are the token lists themselves.
_QUARTER = f"(CASE WHEN p < {DEPTH} + (n - {DEPTH}) // 4 THEN 0 WHEN p < {DEPTH} + (n - {DEPTH}) * 2 // 4 THEN 1 WHEN p < {DEPTH} + (n - {DEPTH}) * 3 // 4 THEN 2 ELSE 3 END)"
OP8_SQL = f"""
WITH d AS MATERIALIZED (SELECT DISTINCT doc_id, text, coalesce(text, '') AS whole FROM documents),
l AS MATERIALIZED (SELECT doc_id, text, unnest(string_split(whole, chr(10))) AS line, generate_subscripts(string_split(whole, chr(10)), 1) - 1 AS pos FROM d),
t AS (SELECT doc_id, text, pos, list_filter(regexp_split_to_array(regexp_replace(line, '[^\\x20\\x09-\\x0D]*[0-9][^\\x20\\x09-\\x0D]*', '{WILD}', 'g'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM l),
c AS MATERIALIZED (SELECT *, len(w) AS n FROM t WHERE len(w) >= {MIN_TOKENS}),
k AS MATERIALIZED (
  SELECT doc_id, text, pos, 0 AS idx, array_to_string(w, ' ') AS key, CASE WHEN n >= {LONG_TOKENS} THEN {LONG_DOCS} ELSE {MIN_DOCS} END AS least FROM c
  UNION ALL SELECT doc_id, text, pos, v.idx, array_to_string(list_transform(range(0, n), lambda p: CASE WHEN p < {DEPTH} OR {_QUARTER} IN (v.i, v.j) THEN w[p + 1] ELSE chr(1) END), ' '), {MIN_DOCS}
    FROM c, (VALUES {", ".join(f"({k + 1}, {i}, {j})" for k, (i, j) in enumerate(KEPT))}) v(idx, i, j) WHERE n >= {DEPTH + MIN_BODY}
  UNION ALL SELECT doc_id, text, pos, q.idx, array_to_string(list_transform(range(0, n), lambda p: CASE WHEN p = {DEPTH} + q.idx - 1 THEN chr(1) ELSE w[p + 1] END), ' '), {MIN_DOCS}
    FROM c JOIN range(1, {MIN_BODY}) q(idx) ON q.idx <= n - {DEPTH} WHERE n BETWEEN {DEPTH + 3} AND {DEPTH + MIN_BODY - 1}),
r AS (SELECT idx, key, count(*) AS n_docs, min(doc_id) AS first_doc FROM (SELECT DISTINCT idx, key, least, doc_id, text FROM k) GROUP BY idx, key, least HAVING count(*) >= least),
h AS MATERIALIZED (SELECT doc_id, text, pos, arg_max((idx, key), (n_docs, -idx)) AS b, bool_or(doc_id <> first_doc) AS gone FROM k JOIN r USING (idx, key) GROUP BY doc_id, text, pos),
m AS (SELECT b, i, CASE WHEN min(x) = max(x) THEN min(x) ELSE '{WILD}' END AS x FROM (SELECT h.b, unnest(c.w) AS x, generate_subscripts(c.w, 1) AS i FROM h JOIN c ON h.doc_id = c.doc_id AND h.text = c.text AND h.pos = c.pos) GROUP BY b, i),
z AS (SELECT b, string_agg(x, ' ' ORDER BY i) AS template FROM m GROUP BY b),
s AS (SELECT doc_id, text, string_agg(template, chr(10) ORDER BY pos) AS said FROM h JOIN z USING (b) GROUP BY doc_id, text),
o AS (SELECT l.doc_id, l.text, count(*) AS n_lines, count(*) FILTER (WHERE h.gone) AS n_dropped,
    coalesce(string_agg(l.line, chr(10) ORDER BY l.pos) FILTER (WHERE h.gone IS NOT TRUE), '') AS kept
  FROM l LEFT JOIN h ON l.doc_id = h.doc_id AND l.text = h.text AND l.pos = h.pos GROUP BY l.doc_id, l.text)
SELECT a.doc_id, o.n_lines, o.n_dropped, length(o.kept) AS kept_chars, sha256(o.kept) AS kept_sha256, sha256(coalesce(s.said, '')) AS templates_sha256
FROM documents a JOIN o ON a.doc_id = o.doc_id AND a.text IS NOT DISTINCT FROM o.text LEFT JOIN s ON a.doc_id = s.doc_id AND a.text = s.text
"""
