"""Secret scan with corpus-wide ownership frequency; DataFrame functions only.

Match positions come from splitting a text at the matches: the lengths of the pieces and of the matches add up to
code-point offsets.  Candidates are hashed, counted by distinct repositories and owners over the whole corpus, and a value
that several owners hold is an example that was copied, while one owner's value looks live.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, docs_of, hot_join, let, running, text_column

#: Kinds and patterns, in the order that breaks ties of the start.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
#: Spans that the method adds: service tokens with a well-known prefix, and private keys.
PREFIXED = r"\b(?:ghp|gho|ghs|glpat|xox[abprs]|sk_live|sk_test|rk_live)[_-][A-Za-z0-9_-]{16,}"
_FOOTER = r"-----END [A-Z ]{0,30}PRIVATE KEY-----"
#: A private key, from header through body to footer; group 1 is the body.  Without a footer before the next five dashes the
#: body is base64: runs of 16 characters or more, or runs that fill their line.  Possessive, as plain groups recurse in Java.
_BREAK, _BETWEEN = r"(?:\r?+\n|\\r?+\\?+n)", r"(?:\\[nrt]|[\s\"'+,>#*|/])"
_FIELDS = rf"(?:(?:\s|\\[nr])*+(?:Proc-Type|DEK-Info|Version|Comment):[^\r\n\\]*+)*+(?:{_BREAK}(?=\s|\\[nr]))?+"
_LINE = rf"{_BREAK}[ \t>#*|\"']*+[A-Za-z0-9+/]++=*+(?=[ \t]*+(?:[\r\n]|\\[nr]|[\"']|\z))"
_BASE64 = rf"(?:{_FIELDS}(?:{_BETWEEN}*+[A-Za-z0-9+/]{{16,}}+=*+|{_LINE})++)?+"
PRIVATE = rf"-----BEGIN [A-Z ]{{0,30}}PRIVATE KEY-----((?:[^-]++|-(?!----))*+(?={_FOOTER})|{_BASE64})(?:{_FOOTER})?+"
KINDS = {"assign": ASSIGN, "access": ACCESS, "hex": HEX, "prefixed": PREFIXED, "private": PRIVATE}
BASE = ("assign", "access", "hex")
#: What line breaks, quotes and indentation add to a key body: the same key counts as one value however it is laid out.
LAYOUT = r"\\[nrt]|[^A-Za-z0-9+/=]"
LEAST_VALUE = 6
#: A value that at least so many owners hold counts as a copied example.
EXAMPLE_OWNERS = 3


_SPAN = "struct<start:long,end:long,o:int,kind:string,value:string>"


def _matches(text: Column, kind: str) -> Column:
    """array<struct(gap, found, value)> of the pattern's leftmost non-overlapping matches, gap the text before each."""
    pattern = F.lit(KINDS[kind])
    found = F.regexp_extract_all(text, pattern, F.lit(0))
    pieces = F.split(text, KINDS[kind], -1)
    value = F.regexp_extract_all(text, pattern, F.lit(2)) if kind == "assign" else found
    if kind == "private":
        value = F.transform(F.regexp_extract_all(text, pattern, F.lit(1)), lambda b: F.regexp_replace(b, LAYOUT, ""))
    rows = F.arrays_zip(F.transform(pieces, F.length).alias("gap"), found.alias("found"), value.alias("value"))
    rows = F.filter(rows, lambda x: x["found"].isNotNull())
    return F.when(text.rlike(KINDS[kind]), rows).otherwise(F.array().cast("array<struct<gap:int,found:string,value:string>>"))


def _placed(kind: Column) -> Column:
    """The spans of kind(o, kind, rows)."""

    def spans(rows: Column) -> Column:
        ends = running(F.transform(rows, lambda y: (y["gap"] + F.length(y["found"])).cast("long")), F.lit(0).cast("long"), lambda a, b: a + b)
        one = lambda y, end: F.struct((end - F.length(y["found"])).alias("start"), end.alias("end"), kind["o"].alias("o"), kind["kind"].alias("kind"), y["value"].alias("value"))
        return F.filter(F.zip_with(rows, ends, one), lambda s: (s["kind"] != "assign") | (F.length(s["value"]) >= LEAST_VALUE))

    return F.when(F.size(kind["rows"]) > 0, let(kind["rows"], spans)).otherwise(F.array().cast(f"array<{_SPAN}>"))


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with ``found``: every span of every kind, by start, then kind; values as SHA-256."""
    body = text_column(text)
    kinds = F.array(*[F.struct(F.lit(i).alias("o"), F.lit(kind).alias("kind"), _matches(body, kind).alias("rows")) for i, kind in enumerate(KINDS)])
    found = F.array_sort(F.flatten(F.transform(kinds, _placed)))
    found = F.transform(found, lambda s: F.struct(s["start"], s["end"], s["kind"].alias("kind"), F.sha2(s["value"], 256).alias("value")))
    return docs.withColumn("found", found)


def owners(found: DataFrame) -> DataFrame:
    """found(value, repo, owner) -> (value, w rows, n_repos, n_owners); distinct counts by two combinable aggregations."""
    rows = found.groupBy("value", "owner", "repo").agg(F.count("*").alias("w"))
    rows = rows.groupBy("value", "owner").agg(F.sum("w").alias("w"), F.count("repo").alias("n_repos"))
    return rows.groupBy("value").agg(F.sum("w").alias("w"), F.sum("n_repos").alias("n_repos"), F.count("owner").alias("n_owners"))


def secrets(docs: DataFrame, text: str = "text", repo: str = "doc_id", owner: str = "source", example_owners: int = EXAMPLE_OWNERS) -> DataFrame:
    """docs -> (doc_id, t, found): found holds start, end, kind, value hash, n_repos, n_owners and live for each span.

    ``t`` is a hash of the text, which with doc_id tells repeated rows apart.  Null or empty texts have no spans.  A null
    owner or repository counts as none, so such a value looks live.  Spans of different kinds may overlap.  The value of a
    private key is its body; a header without any holds no key and is never live.  Equal rows get equal spans, each once.
    """
    scratch = Scratch(docs.sparkSession)
    slim = docs.select("doc_id", text_column(text).alias("text"), F.col(repo).alias("repo"), F.col(owner).cast("string").alias("owner"))
    scanned = scan(slim).select("doc_id", F.xxhash64("text").alias("t"), "repo", "owner", "found")
    scanned = scratch.save(scanned, "scanned")
    each = scanned.where("size(found) > 0").select("doc_id", "t", "repo", "owner", F.explode("found").alias("s"))
    each = each.select("doc_id", "t", "repo", "owner", "s.*")
    counted = scratch.save(owners(each), "owners")
    judged = hot_join(each.drop("repo", "owner").distinct(), counted, ["value"], "w")
    live = (F.col("n_owners") < example_owners) & (F.col("value") != F.sha2(F.lit(""), 256))
    span = F.struct("start", F.when(F.col("kind").isin(*BASE), F.array_position(F.array(*map(F.lit, KINDS)), F.col("kind"))).otherwise(9).alias("o"), "end", "kind", "value", "n_repos", "n_owners", live.alias("live"))
    by_doc = judged.groupBy(F.col("doc_id").alias("d"), F.col("t").alias("u")).agg(F.array_sort(F.collect_list(span)).alias("judged"))
    out = scanned.join(by_doc, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("t") == F.col("u")), "left")
    return out.select("doc_id", "t", F.coalesce("judged", F.array().cast(by_doc.schema["judged"].dataType)).alias("found"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_example for every document."""
    found = secrets(docs_of(spark, sf_dir))
    count = lambda kind: F.size(F.filter("found", lambda s: s["kind"] == kind)).cast("long")
    return found.select(
        "doc_id",
        *[count(kind).alias(f"n_{kind}") for kind in BASE],
        F.sha2(_listed(F.filter("found", lambda s: s["kind"].isin(*BASE))), 256).alias("base_sha256"),
        _listed(F.col("found")).alias("spans"),
        F.size(F.filter("found", lambda s: s["live"])).cast("long").alias("n_live"),
        F.size(F.filter("found", lambda s: ~s["live"])).cast("long").alias("n_example"),
    )


def _cut(body: Column, live: Column, mark: str) -> Column:
    """body without the spans of ``live`` (by start), each run of overlapping spans replaced by one mark.

    Pieces are taken from the text in a code of four bytes a character, so each costs its own length wherever it stands.
    """
    longs = lambda name: F.transform(live, lambda s: s[name].cast("long"))

    def glued(wide: Column, start: Column, before: Column) -> Column:
        # a span opens a run of its own where it starts at or behind all earlier ends; before: the furthest end so far
        opens = F.filter(F.transform(start, lambda s, i: F.struct(s.alias("to"), F.get(before, i).alias("from"))), lambda g: g["to"] >= g["from"])
        tail = F.array(F.struct((F.octet_length(wide) / 4).cast("long").alias("to"), F.try_element_at(before, F.lit(-1)).alias("from")))
        piece = lambda g: F.decode(F.substring(wide, (g["from"] * 4 + 1).cast("int"), ((g["to"] - g["from"]) * 4).cast("int")), "UTF-32")
        return F.array_join(F.transform(F.concat(opens, tail), piece), mark)

    zero = F.lit(0).cast("long")
    far = F.concat(F.array(zero), running(longs("end"), zero, lambda a, b: F.greatest(a, b)))
    return let(F.encode(body, "UTF-32"), lambda wide: let(longs("start"), lambda start: let(far, lambda before: glued(wide, start, before))))


def redacted(docs: DataFrame, text: str = "text", mark: str = "[SECRET]") -> DataFrame:
    """docs with live-looking secrets replaced by ``mark`` (copied examples stay); n_chars, if there, follows the text.

    Spans of several kinds that overlap become one mark.  Null texts stay null, texts without live secrets stay as they are,
    and equal rows are treated alike.  Columns of docs may have any name but those starting with ``_redact_``.
    """
    live = secrets(docs, text).select(F.col("doc_id").alias("_redact_d"), F.col("t").alias("_redact_t"), F.filter("found", lambda s: s["live"]).alias("_redact_live"))
    live = live.where("size(_redact_live) > 0").dropDuplicates(["_redact_d", "_redact_t"])
    body = text_column(text)
    joined = docs.withColumn("_redact_u", F.xxhash64(body)).join(live, F.col("doc_id").eqNullSafe(F.col("_redact_d")) & (F.col("_redact_u") == F.col("_redact_t")), "left")
    # a column of its own: beside an alias "text", a lambda's "text" would mean the new text
    joined = joined.withColumn("_redact_new", F.when(F.col("_redact_live").isNotNull(), _cut(body, F.col("_redact_live"), mark)).otherwise(F.col(text)))
    length = F.when(F.col("_redact_live").isNotNull(), F.length("_redact_new").cast("long")).otherwise(F.col("n_chars")).alias("n_chars") if "n_chars" in docs.columns else None
    named = {c: F.col(c) for c in docs.columns} | {text: F.col("_redact_new").alias(text)} | ({"n_chars": length} if length is not None else {})
    return joined.select(*[named[c] for c in docs.columns])
