"""Secret scan with multipart credential linking, in DataFrame operations only.

Strong findings stand alone: assignments, access identifiers, long hex strings.  Weak candidates do not:
assignments, access identifiers and hex strings that are too short to be strong, other spellings of a key,
opaque 40-character strings; account names and mail addresses; urls and bare host addresses.  They are
reported only where complementary parts occur together: a secret needs an identifier or an endpoint in
its scope, an identifier or an endpoint needs a secret.  A scope reaches `scope` code points between the
starts of two findings.  Linked findings, strong ones too, form credentials: in order of their starts, one
that lies beyond the scope of the one before begins the next credential, which goes by its first start.

The link is an interval join: findings are put in cells as wide as a scope and each cell keeps the first
and last start of each part, so a finding meets its own cell and the two beside it, three rows at most,
however many findings stand there.

Most texts hold nothing: plain substring tests and two simple patterns decide which patterns are tried at
all, and weak identifiers and endpoints are looked for only where a secret may be.

Defined cases: a null or empty text has no findings; repeated rows give a row each with the same
findings; a null id is kept; an empty table gives an empty result; further columns are ignored by the
scan and kept by the redaction.  Positions are code points, ends exclusive.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .shared import materialize


@dataclass(frozen=True)
class Form:
    """A pattern, the group whose length counts, and what a match is: (kind, least length, weak) by falling length.

    part: which part of a credential it is.  hints: what a text must have for the pattern to be tried (in
    lower case if any_case); gate: or what pattern must be found.  also: what a weak match's value must hold.
    """

    pattern: str
    group: int
    part: str
    tiers: tuple[tuple[str, int, bool], ...]
    hints: tuple[str, ...] = ()
    any_case: bool = True
    gate: str = ""
    also: tuple[str, ...] = ()

    @property
    def all_weak(self) -> bool:
        return all(weak for _, _, weak in self.tiers)


_NO_WORD_BEFORE, _NO_WORD_AFTER = "(?<![A-Za-z0-9_])", "(?![A-Za-z0-9_])"
# The patterns and least lengths of the base kinds, each with its weak sibling.
BASE_FORMS = (
    Form(
        r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, "secret", (("assign", 6, False), ("short_assign", 3, True)),
        ("password", "passwd", "secret", "token", "apikey", "api_key"),
    ),
    Form(r"AKIA[A-Z0-9]+", 0, "identifier", (("access", 20, False), ("short_access", 12, True)), ("AKIA",), False),
    Form(r"[0-9a-f]{16,}", 0, "secret", (("hex", 24, False), ("short_hex", 16, True)), gate=r"[0-9a-f]{16}", also=("[0-9]", "[a-f]")),
)
# Forms of weak candidates.
WEAK_FORMS = (
    Form(_NO_WORD_BEFORE + r"""(?i)(pwd|pass|pin|auth|bearer|credential|access_?key|private_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, "secret", (("weak_assign", 4, True),), ("pwd", "pass", "pin", "auth", "bearer", "credential", "access", "private")),
    Form(
        r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/]*[0-9])(?=[A-Z0-9+/]*[a-z])(?=[a-z0-9+/]*[A-Z])[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/_=-])", 0, "secret", (("opaque", 40, True),),
        gate="[A-Za-z0-9+/]{40}",
    ),
    Form(_NO_WORD_BEFORE + r"""(?i)(user(?:_?name)?|login|account|client_?id|access_?key_?id)["']?\x20*[:=]\x20*["']?([A-Za-z0-9@._-]+)""", 2, "identifier", (("account", 3, True),), ("user", "login", "account", "client", "access")),
    Form(r"[A-Za-z0-9._%+-]{1,64}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){1,8}", 0, "identifier", (("mailbox", 5, True),), ("@",)),
    Form(_NO_WORD_BEFORE + r"""(?i)[a-z][a-z0-9+.-]{1,15}://[^\s"'<>]{4,}""", 0, "endpoint", (("endpoint", 7, True),), ("://",)),
    Form(_NO_WORD_BEFORE + r"[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?::[0-9]{2,5})?" + _NO_WORD_AFTER, 0, "endpoint", (("host", 7, True),), (".",)),
)
FORMS = BASE_FORMS + WEAK_FORMS
#: Kinds in the order in which findings with one start are listed, and what each is.
KINDS = tuple(k for k, _, weak in (t for f in FORMS for t in f.tiers) if not weak) + tuple(k for k, _, weak in (t for f in FORMS for t in f.tiers) if weak)
BASE = KINDS[: len(BASE_FORMS)]
SECRETS = tuple(k for f in FORMS if f.part == "secret" for k, _, _ in f.tiers)
SCOPE = 256


def _matches(text: Column, form: Form) -> Column:
    """array<struct<form, gap, size, value, fine>>: the pattern's matches in order; gap: what lies before one."""
    found = F.regexp_extract_all(text, F.lit(form.pattern), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(form.pattern), F.lit(form.group)) if form.group else found
    fine = lambda v: reduce(lambda a, p: a & v.rlike(p), form.also, F.lit(True))
    rows = F.transform(
        F.arrays_zip(F.transform(F.split(text, form.pattern, -1), F.length).alias("gap"), found.alias("found"), value.alias("value")),
        lambda x: F.struct(
            F.lit(FORMS.index(form)).alias("form"), x["gap"].alias("gap"), F.length(x["found"]).alias("size"), F.length(x["value"]).alias("value"),
            fine(x["value"]).alias("fine"),
        ),
    )
    return F.slice(rows, 1, F.size(found))


def _tried(form: Form) -> Column:
    """Whether text may hold the form at all."""
    if form.gate:
        return F.col("text").rlike(form.gate)
    within = F.col("low") if form.any_case else F.col("text")
    return reduce(lambda a, h: a | within.contains(h), form.hints, F.lit(False))


def candidates(docs: DataFrame) -> DataFrame:
    """(doc_id, key, kind, start, end): every match that is long enough; key tells texts of one id apart."""
    none = F.array().cast("array<struct<form:int,gap:int,size:int,value:int,fine:boolean>>")
    tried = [f"tried{k}" for k in range(len(FORMS))]
    texts = docs.select("doc_id", "text", F.lower("text").alias("low"), F.xxhash64("text").alias("key")).where(F.length("text") > 0)
    secret = [f for f in FORMS if f.part == "secret"]
    texts = texts.select("doc_id", "key", "text", "low", *(_tried(f).alias(t) for f, t in zip(FORMS, tried, strict=True) if f in secret or not f.all_weak))
    may_hold = reduce(lambda a, b: a | b, (F.col(t) for f, t in zip(FORMS, tried, strict=True) if f in secret))
    lists = []
    for form, t in zip(FORMS, tried, strict=True):
        # a weak identifier or endpoint alone is never reported
        wanted = F.col(t) if t in texts.columns else may_hold & _tried(form)
        lists.append(F.when(wanted, _matches(F.col("text"), form)).otherwise(none))
    rows = (
        texts.select("doc_id", "key", F.array(*lists).alias("lists"))
        .select("doc_id", "key", F.explode("lists").alias("list"))
        .select("doc_id", "key", F.posexplode("list").alias("n", "m"))
        .select("doc_id", "key", "n", "m.*")
    )
    rows = materialize(rows, "matches").dropDuplicates(["doc_id", "key", "form", "n"])
    until = W.partitionBy("doc_id", "key", "form").orderBy("n").rowsBetween(W.unboundedPreceding, 0)
    end = F.sum(F.col("gap").cast("long") + F.col("size")).over(until)
    kind = F.lit(None).cast("string")
    for k, form in enumerate(FORMS):
        for name, least, weak in reversed(form.tiers):
            kind = F.when((F.col("form") == k) & (F.col("value") >= least) & (F.col("fine") if weak else F.lit(True)), name).otherwise(kind)
    return rows.withColumn("end", end).select("doc_id", "key", kind.alias("kind"), (F.col("end") - F.col("size")).alias("start"), "end").where("kind is not null")


def findings(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """(doc_id, key, kind, start, end, credential) of strong findings and of the weak ones that are linked; credential: null if not linked."""
    cols = ["doc_id", "key", "kind", "start", "end"]
    every = candidates(docs).withColumn("secret", F.col("kind").isin(*SECRETS)).withColumn("cell", F.floor(F.col("start") / scope))
    every = materialize(every, "candidates")
    cells = every.groupBy("doc_id", "key", "secret", "cell").agg(F.min("start").alias("first"), F.max("start").alias("last"))
    cells = cells.select(
        F.col("doc_id").alias("cid"), F.col("key").alias("ckey"), (~F.col("secret")).alias("csecret"), "first", "last", F.col("cell").alias("ccell")
    )
    met = every.withColumn("beside", F.explode(F.array(F.col("cell") - 1, F.col("cell"), F.col("cell") + 1)))
    joined = met.join(
        cells,
        met["doc_id"].eqNullSafe(cells["cid"]) & (met["key"] == cells["ckey"]) & (met["secret"] == cells["csecret"]) & (met["beside"] == cells["ccell"]),
    )
    near = (
        (F.col("beside") == F.col("cell"))
        | ((F.col("beside") < F.col("cell")) & (F.col("start") - F.col("last") <= scope))
        | ((F.col("beside") > F.col("cell")) & (F.col("first") - F.col("start") <= scope))
    )
    linked = joined.where(near).select(*cols).distinct()
    before = W.partitionBy("doc_id", "key").orderBy("start", "end", "kind")
    begins = F.col("start") - F.lag("start").over(before)
    linked = linked.withColumn("begins", F.when(begins.isNull() | (begins > scope), F.col("start")))
    linked = linked.select(*cols, F.max("begins").over(before.rowsBetween(W.unboundedPreceding, 0)).alias("credential"))
    alone = every.where(F.col("kind").isin(*BASE)).select(*cols, F.lit(None).cast("long").alias("credential"))
    return linked.unionByName(alone).groupBy(*cols).agg(F.max("credential").alias("credential"))


def scan(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """For each row of docs(doc_id, text): doc_id, key, and spans array<struct<start, rank, kind, end, credential>> in order."""
    docs = docs.select("doc_id", "text")
    rank = F.array_position(F.lit(list(KINDS)), F.col("kind")).cast("int")
    found = findings(docs, scope).withColumn("rank", rank)
    spans = found.groupBy("doc_id", "key").agg(F.sort_array(F.collect_list(F.struct("start", "rank", "kind", "end", "credential"))).alias("spans"))
    spans = spans.select(F.col("doc_id").alias("found_id"), F.col("key").alias("found_key"), "spans")
    rows = docs.select("doc_id", F.xxhash64("text").alias("key"))
    return rows.join(spans, rows["doc_id"].eqNullSafe(spans["found_id"]) & (rows["key"] == spans["found_key"]), "left").select(
        "doc_id", "key", F.coalesce("spans", F.array().cast(spans.schema["spans"].dataType)).alias("spans")
    )


def redact(docs: DataFrame, scope: int = SCOPE, mark: str = "[SECRET]") -> DataFrame:
    """docs with each finding in text, and n_chars if there is one, replaced by mark; overlaps count as one."""
    found = scan(docs, scope).where(F.size("spans") > 0)
    found = found.select(F.col("doc_id").alias("__id"), F.col("key").alias("__key"), F.col("spans").alias("__spans")).dropDuplicates(["__id", "__key"])
    joined = docs.join(found, docs["doc_id"].eqNullSafe(found["__id"]) & (F.xxhash64(docs["text"]) == found["__key"]), "left")
    start = F.struct(F.lit("").alias("out"), F.lit(0).cast("long").alias("at"))

    def step(state: Column, span: Column) -> Column:
        fresh = span["start"] >= state["at"]
        out = F.when(fresh, F.concat(state["out"], F.substr(F.col("text"), (state["at"] + 1).cast("int"), (span["start"] - state["at"]).cast("int")), F.lit(mark)))
        return F.struct(out.otherwise(state["out"]).alias("out"), F.greatest(state["at"], span["end"]).alias("at"))

    whole = F.aggregate("__spans", start, step, lambda s: F.concat(s["out"], F.substr(F.col("text"), (s["at"] + 1).cast("int"))))
    text = F.when(F.col("__spans").isNotNull(), whole).otherwise(F.col("text"))
    joined = joined.withColumn("text", text)
    if "n_chars" in docs.columns:
        joined = joined.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars")))
    return joined.select(*docs.columns)


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op1_secret_scan(spark, sf_dir) -> DataFrame:
    found = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    count = lambda name: F.size(F.filter("spans", lambda s: s["kind"] == name)).cast("long")
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE))
    return found.select(
        "doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"),
        F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"),
        F.array_join(F.transform("spans", lambda s: F.coalesce(s["credential"].cast("string"), F.lit("-"))), ",").alias("credentials"),
    )


def oracle_sql(scope: int = SCOPE) -> str:
    """The scan in DuckDB's SQL.  Its patterns lack look-around: words begin and end at ASCII bounds there, opaque strings are runs that are then tested."""
    text = lambda s: "'" + s.replace("'", "''") + "'"
    parts = []
    for form in FORMS:
        pattern = form.pattern.replace(_NO_WORD_BEFORE, r"\b").replace(_NO_WORD_AFTER, r"\b")
        also = " AND ".join(f"regexp_matches(v, '{p}')" for p in form.also) or "true"
        if form.gate.endswith("{40}"):
            pattern = "[A-Za-z0-9+/_=-]+"
            also = "regexp_full_match(v, '[A-Za-z0-9+/]{40}') AND regexp_matches(v, '[0-9]') AND regexp_matches(v, '[a-z]') AND regexp_matches(v, '[A-Z]')"
        value = f"regexp_extract_all(t, {text(pattern)}, {form.group})"
        kind = "CASE " + " ".join(f"WHEN length(v) >= {least}{f' AND {also}' if weak else ''} THEN {text(name)}" for name, least, weak in form.tiers) + " END"
        parts.append(
            f"""SELECT r, {kind} AS kind, {str(form.part == "secret").lower()} AS secret,
       sum(length(gap) + length(f)) OVER (PARTITION BY r ORDER BY n) AS e, length(f) AS size
FROM (SELECT r, n, fs[n] AS f, vs[n] AS v, gs[n] AS gap FROM (SELECT r, fs, vs, gs, unnest(range(1, len(fs) + 1)) AS n
      FROM (SELECT r, regexp_extract_all(t, {text(pattern)}) AS fs, {value} AS vs, string_split_regex(t, {text(pattern)}) AS gs FROM d)))"""
        )
    names = "[" + ", ".join(text(k) for k in KINDS) + "]"
    base = f"kind IN ({', '.join(text(k) for k in BASE)})"
    count = lambda n: f"count(*) FILTER (kind = {text(n)})"
    joined = "string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, rank, e)"
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
m AS ({" UNION ALL ".join(parts)}),
c AS (SELECT r, kind, list_position({names}, kind) AS rank, secret, CAST(e - size AS BIGINT) AS s, CAST(e AS BIGINT) AS e FROM m WHERE kind IS NOT NULL),
k AS (SELECT *, EXISTS (SELECT 1 FROM c b WHERE a.r = b.r AND a.secret <> b.secret AND abs(a.s - b.s) <= {scope}) AS linked FROM c a),
g AS (SELECT r, kind, rank, s, e, CASE WHEN s - lag(s) OVER w <= {scope} THEN NULL ELSE s END AS begins FROM k WHERE linked WINDOW w AS (PARTITION BY r ORDER BY s, e, kind)),
o AS (SELECT r, kind, rank, s, e, max(begins) OVER (PARTITION BY r ORDER BY s, e, kind ROWS UNBOUNDED PRECEDING) AS credential FROM g
      UNION ALL SELECT r, kind, rank, s, e, NULL FROM k WHERE NOT linked AND {base}),
x AS (SELECT r, {count("assign")} AS n_assign, {count("access")} AS n_access, {count("hex")} AS n_hex,
             coalesce({joined} FILTER ({base}), '') AS base, {joined} AS spans, string_agg(coalesce(CAST(credential AS VARCHAR), '-'), ',' ORDER BY s, rank, e) AS credentials FROM o GROUP BY r)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, coalesce(credentials, '') AS credentials
FROM d LEFT JOIN x ON d.r = x.r
"""


OP1_SQL = oracle_sql()
