"""Personal data: four kinds found by pattern, and the terms that would still give their owners away.

Base spans are e-mail addresses, IP addresses, card numbers (Luhn) and telephone numbers. The information-theoretic
step then asks how strongly a term near such an entity reveals which entity it is. A term t co-occurs with entity e in
n(t, e) different texts and stands in n(t) different texts of the whole corpus of N; e is in n(e). Copies of a text
count once everywhere. Its disclosure is the pointwise mutual information
log(n(t, e) N / (n(t) n(e))), and e's share of t is n(t, e) / n(t). Terms with at least ``SUPPORT`` texts, a share
of at least ``SHARE`` and a disclosure of at least ``DISCLOSURE`` reveal e.

That needs repetition. What an address says itself does not: a term that is a part of the local part of an e-mail
address reveals it from the first text on, without a share, if its disclosure is as high (in ``the.94@`` it is not, as
"the" stands everywhere). So does a secret, a long word of letters and digits, which is an entity of its own and reveals itself.
Revealing terms are spans of kind ``term`` wherever they stand in a text that has their
entity. In the sanitised text such a term is removed if it stands with no other entity, and generalised to its
shape if it does; base spans become a placeholder of their kind.

Everything is built-in functions. All counts are exact: n(t) is an aggregation by term over all different texts, joined
to the candidates by equality.

Defined cases: NULL texts count as empty and have no span; repeated rows repeat (as one text); extra columns are
ignored by ``spans`` and kept by ``sanitise``; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.io import materialize

#: Fixed patterns, in the order in which kinds are listed. A run of characters that could begin a match is only tried
#: from its start, or from where the last match ended, which keeps long runs linear and leaves the matches the same.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)",
    "card": r"[0-9]([\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for a kind to be looked for at all.
NEEDS = {"email": "instr(t, '@') > 0", "ip": "instr(t, '.') > 0", "card": "true", "phone": "instr(t, '+') > 0"}
DIGITS = "regexp_replace(v, '[^0-9]', '')"
LUHN = (
    "aggregate(sequence(1, length(d)), 0, (a, i) -> a + CASE WHEN i % 2 = 1 THEN int(substring(d, -i, 1)) "
    "ELSE int(substring(d, -i, 1)) * 2 - CASE WHEN int(substring(d, -i, 1)) > 4 THEN 9 ELSE 0 END END) % 10 = 0"
)
#: What a match must also satisfy; v is the match, d its digits.
VALID = {
    "email": "true",
    "ip": "forall(split(v, '[.]'), x -> length(ltrim('0', x)) <= 3 AND int(right(concat('0', x), 3)) <= 255)",
    "card": f"length({DIGITS}) BETWEEN 14 AND 19 AND {LUHN.replace('(d', '(' + DIGITS)}",
    "phone": f"length({DIGITS}) BETWEEN 10 AND 15",
}
SPAN = "array<struct<s:int,k:int,e:int,v:string>>"
KINDS = [*PATTERNS, "term"]
#: Words this many characters before and after a base span are its context.
REACH = 60
SUPPORT, SHARE, DISCLOSURE = 3, 0.5, 3.0
CHAR = r"[\p{L}\p{N}\x27_-]"
WORD, NO_WORD = CHAR + "+", r"[^\p{L}\p{N}\x27_-]+"
ENTITY = "xxhash64(x.k, lower(x.v))"
#: What may be a secret: a word with letters and digits, all ASCII, of this length or more. As an entity it has a kind of its own.
SECRET = rf"(?<!{CHAR})(?=[A-Za-z_-]*+[0-9])(?=[0-9_-]*+[A-Za-z])[A-Za-z0-9_-]{{20,}}+(?!{CHAR})"
SECRET_KIND = len(KINDS)
#: Shorter parts of an address are no name.
LEAST_NAME = 3


def sql_text(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def positions(text: str, pattern: str | None, kind: int, valid: str, expression: str | None = None) -> str:
    """SQL for the matches of a pattern as spans: the pieces between matches give their places, in code points.

    ``expression`` is SQL for a pattern that differs by row.
    """
    p = expression or sql_text(pattern)
    step = (
        "(a, i) -> named_struct('p', a.p + length(g[i]) + length(m[i]), 'o', array_append(a.o, "
        f"named_struct('s', a.p + length(g[i]), 'k', {kind}, 'e', a.p + length(g[i]) + length(m[i]), 'v', m[i])))"
    )
    # transform over one element binds the matches and the pieces to names
    walk = (
        f"transform(array(named_struct('m', regexp_extract_all({text}, {p}, 0), 'g', split({text}, {p}, -1))), b -> "
        f"aggregate(slice(sequence(0, size(b.m)), 1, size(b.m)), named_struct('p', 0, 'o', CAST(array() AS {SPAN})), "
        f"{step.replace('g[i]', 'b.g[i]').replace('m[i]', 'b.m[i]')}, a -> a.o))[0]"
    )
    return f"filter({walk}, x -> {valid.replace('v,', 'x.v,')})"


def base_spans(docs: DataFrame, *keep) -> DataFrame:
    """``keep``, ``t`` (the text or ''), ``b``: all base spans ordered by start, then kind, and ``c``: what may be secrets."""
    found = docs.select(*keep, F.coalesce("text", F.lit("")).alias("t"))
    some = {k: f"{NEEDS[k]} AND t rlike {sql_text(p)}" for k, p in PATTERNS.items()}
    each = [
        f"CASE WHEN {some[k]} THEN {positions('t', p, n, VALID[k])} ELSE CAST(array() AS {SPAN}) END"
        for n, (k, p) in enumerate(PATTERNS.items())
    ]
    secrets = f"CASE WHEN t rlike {sql_text(SECRET)} THEN {positions('t', SECRET, SECRET_KIND, 'true')} ELSE CAST(array() AS {SPAN}) END"
    return found.withColumn("b", F.expr(f"array_sort(concat({', '.join(each)}))")).withColumn("c", F.expr(secrets))


def contexts(found: DataFrame, row: str) -> DataFrame:
    """``row, entity, term, word, s, e``: every word near a base span, with its place in the text."""
    near = found.filter("size(b) > 0").selectExpr(row, "t", "b", "explode(b) AS x").selectExpr(
        row, "b", f"{ENTITY} AS entity",
        f"greatest(0, x.s - {REACH}) AS left_at", f"substring(t, greatest(0, x.s - {REACH}) + 1, least({REACH}, x.s)) AS left_text",
        "x.e AS right_at", f"substring(t, x.e + 1, {REACH}) AS right_text",
    )
    # a word that the reach cuts off is no word
    sides = near.selectExpr(
        row, "b", "entity",
        "stack(2, left_at, CASE WHEN left_at > 0 THEN regexp_replace(left_text, '^[^\\\\s]+', '') ELSE left_text END, left_at + length(left_text),"
        f" right_at, CASE WHEN length(right_text) = {REACH} THEN regexp_replace(right_text, '[^\\\\s]+$', '') ELSE right_text END, right_at)"
        " AS (at, side, stop)",
    )
    placed = sides.selectExpr(
        row, "b", "entity",
        # the left side has lost its first word, so its places count from its end
        f"explode({positions('side', WORD, 4, 'true')}) AS w", "CASE WHEN stop = at THEN at ELSE stop - length(side) END AS at",
    )
    words = placed.selectExpr(
        row, "b", "entity", "lower(w.v) AS term", "w.v AS word", "at + w.s AS s", "at + w.e AS e"
    )
    return words.filter("length(term) > 1 AND NOT exists(b, x -> x.s < e AND s < x.e)").drop("b")


def distinct_texts(docs: DataFrame) -> DataFrame:
    """``t``: every different text once, in lower case."""
    texts = docs.filter("text IS NOT NULL").selectExpr("md5(text) AS key", "lower(text) AS t")
    return texts.groupBy("key").agg(F.first("t").alias("t")).select("t")


def term_counts(texts: DataFrame) -> DataFrame:
    """``term, n``: in how many of the texts each term stands."""
    words = texts.selectExpr("explode(array_distinct(split(t, '[^\\\\p{L}\\\\p{N}\\'_-]+'))) AS term")
    return words.groupBy("term").agg(F.count(F.lit(1)).alias("n"))


def named(some: DataFrame) -> DataFrame:
    """``entity, term, key``: the words of the texts ``some(key, t, b)`` that their own e-mail addresses contain."""
    blank = f"regexp_replace(lower(t), {sql_text(PATTERNS['email'])}, ' ')"
    words = some.selectExpr("key", f"split({blank}, {sql_text(NO_WORD)}) AS w", "explode(filter(b, x -> x.k = 0)) AS x")
    parts = words.selectExpr(
        "key", f"{ENTITY} AS entity", "array_intersect(split(lower(substring_index(x.v, '@', 1)), '[^\\\\p{L}]+'), w) AS both"
    ).selectExpr("key", "entity", "explode(both) AS term")
    return parts.filter(f"length(term) >= {LEAST_NAME}").distinct()


def entities(some: DataFrame) -> DataFrame:
    """``key, entity, secret``: what each text has to protect; secret: the secret itself as a term, else NULL."""
    each = some.selectExpr("key", "explode(concat(b, c)) AS x")
    return each.selectExpr("key", f"{ENTITY} AS entity", f"CASE WHEN x.k = {SECRET_KIND} THEN lower(x.v) END AS secret").distinct()


def disclosing(near: DataFrame, some: DataFrame, docs: DataFrame) -> DataFrame:
    """``entity, term, alone``: the terms that reveal an entity of the texts ``some``; alone: they stand near no other."""
    beside = near.select("entity", "term", "key").distinct()
    having = entities(some)
    itself = having.filter("secret IS NOT NULL").select("key", "entity", F.col("secret").alias("term"))
    own = named(some).unionByName(itself).withColumn("own", F.lit(1))
    seen = beside.withColumn("own", F.lit(0)).unionByName(own).groupBy("entity", "term", "key").agg(F.max("own").alias("own"))
    pairs = seen.groupBy("entity", "term").agg(F.count(F.lit(1)).alias("n_te"), (F.max("own") == 1).alias("own"))
    strong = materialize(pairs.filter((F.col("n_te") >= SUPPORT) | F.col("own")), "term-entity")
    sizes = having.groupBy("entity").agg(F.count(F.lit(1)).alias("n_e"))
    spread = pairs.groupBy("term").agg((F.count(F.lit(1)) == 1).alias("alone"))
    total = F.broadcast(docs.agg(F.count_distinct(F.md5("text")).alias("n_all")))
    counted = term_counts(distinct_texts(docs))
    joined = strong.join(counted, "term").join(sizes, "entity").join(spread, "term").crossJoin(total)
    n = F.greatest("n", "n_te")
    return joined.filter(
        (F.col("own") | (F.col("n_te") >= SHARE * n)) & (F.log(F.col("n_te") * F.col("n_all") / (n * F.col("n_e"))) >= DISCLOSURE)
    ).select("entity", "term", "alone")


def keyed(docs: DataFrame, *keep) -> DataFrame:
    """``keep``, ``t``, ``b`` and ``key``, a digest of the text (NULL without entities): equal texts, equal spans."""
    return base_spans(docs, *keep).withColumn("key", F.expr("CASE WHEN size(b) + size(c) > 0 THEN md5(t) END"))


def term_spans(some: DataFrame, docs: DataFrame) -> DataFrame:
    """``key, m``: the spans of disclosing terms in the texts ``some(key, t, b, c)``, each text once."""
    each = some.filter("key IS NOT NULL").groupBy("key").agg(F.first("t").alias("t"), F.first("b").alias("b"), F.first("c").alias("c"))
    each = materialize(each, "pii-texts")
    flagged = disclosing(materialize(contexts(each, "key"), "pii-contexts"), each, docs)
    having = entities(each).select("key", "entity")
    # a term that reveals two entities of a text and stands near others is generalised there
    terms = having.join(flagged, "entity").groupBy("key", "term").agg(F.min("alone").alias("alone"))
    terms = terms.groupBy("key").agg(F.map_from_entries(F.collect_list(F.struct("term", "alone"))).alias("terms"))
    pattern = f"concat('(?iu)(?<!{CHAR})(?:', array_join(map_keys(terms), '|'), ')(?!{CHAR})')".replace("\\", "\\\\")
    found = each.join(terms, "key").selectExpr("key", "b", "terms", f"{positions('t', None, 4, 'true', pattern)} AS w")
    outside = "filter(w, x -> NOT exists(b, y -> y.s < x.e AND x.s < y.e))"
    value = "CASE WHEN coalesce(terms[lower(x.v)], false) THEN '' ELSE x.v END"
    return found.selectExpr("key", f"array_sort(transform({outside}, x -> struct(x.s AS s, x.k AS k, x.e AS e, {value} AS v))) AS m")


ALL_SPANS = f"array_sort(concat(b, coalesce(m, CAST(array() AS {SPAN})))) AS a"


def spans(docs: DataFrame, *keep: str) -> DataFrame:
    """``keep``, ``b`` (base spans) and ``a`` (all spans), ordered by start, then kind; without the texts.

    A span is a struct of start, kind (its place in ``KINDS``), end and value. Ends are exclusive.
    """
    found = keyed(docs, *keep).withColumn("t", F.expr("CASE WHEN key IS NOT NULL THEN t END"))
    found = materialize(found, "pii-found")  # of the texts only those with entities
    # texts without base spans and secrets have no others: they pass without a join, in which their NULL keys would meet in one task
    clean = found.filter("key IS NULL").selectExpr(*keep, "b", "b AS a")
    some = found.filter("key IS NOT NULL").join(term_spans(found, docs), "key", "left")
    return clean.unionByName(some.selectExpr(*keep, "b", ALL_SPANS))


def described(column: str) -> str:
    kinds = "array(" + ", ".join(f"'{k}'" for k in KINDS) + ")"
    return f"array_join(transform({column}, x -> concat({kinds}[x.k], ':', x.s, ':', x.e)), ',')"


def report(docs: DataFrame) -> DataFrame:
    """``doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term`` of every document."""
    counts = [f"CAST(size(filter(a, x -> x.k = {n})) AS BIGINT) AS n_{k}" for n, k in enumerate(KINDS)]
    return spans(docs, "doc_id").selectExpr(
        "doc_id", *counts[:4], f"sha2({described('b')}, 256) AS base_sha256", f"{described('a')} AS spans", counts[4]
    )


def sanitise(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with every span of ``text`` replaced; overlapping spans become one, named after the first."""
    names = "array(" + ", ".join(f"'<{k.upper()}>'" for k in KINDS) + ")"
    # the text between spans, then what stands for each span; a span inside the one before it adds nothing
    shape = f"CASE WHEN x.k < 4 THEN {names}[x.k] WHEN x.v = '' THEN '' WHEN x.v rlike '^\\\\p{{Lu}}' THEN '<NAME>' ELSE '<TERM>' END"
    walk = (
        "aggregate(a, named_struct('p', 0, 'o', CAST('' AS STRING)), (c, x) -> CASE WHEN x.s < c.p THEN "
        "named_struct('p', greatest(c.p, x.e), 'o', c.o) ELSE named_struct('p', x.e, 'o', concat(c.o, "
        f"substring(t, c.p + 1, x.s - c.p), {shape})) END, c -> concat(c.o, substring(t, c.p + 1)))"
    )
    # texts without base spans and secrets have no others: they pass without a join
    own = keyed(docs, *(F.col(f"`{c}`").alias(f"c{n}") for n, c in enumerate(docs.columns)))
    back = [F.col(f"c{n}").alias(c) for n, c in enumerate(docs.columns)]
    clean = own.filter("key IS NULL").select(*back)
    some = own.filter("key IS NOT NULL")
    terms = term_spans(some.select("key", "t", "b", "c"), docs)
    changed = some.join(terms, "key", "left").selectExpr("*", ALL_SPANS).withColumn("new", F.expr(walk))
    at = docs.columns.index("text")
    return clean.unionByName(changed.withColumn(f"c{at}", F.col("new")).select(*back))
