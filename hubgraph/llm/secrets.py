"""Secret scanning over a ledger of content-addressed blobs, in DataFrame functions alone.

Every text, and every earlier version of it, is a blob with its SHA-256 as address. The ledger holds the pairs of
blob and rule version that have been scanned, with their spans. A run scans only pairs that the ledger lacks, one
copy of each blob, and joins the spans back to all rows that hold the blob.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The base kinds in their order, their patterns and least lengths (of group 2 for the first).
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
BASE_KINDS = ("assign", "access", "hex")
#: Kinds of a match that are found by its least length; maximal runs make this the same as matching and then dropping.
RULES = {
    1: {"assign": ASSIGN, "access": r"AKIA[A-Z0-9]{16,}", "hex": r"[0-9a-f]{24,}"},
    2: {"pem": r"-----BEGIN [A-Z ]*PRIVATE KEY-----"},
}
KINDS = {kind: (version, pattern) for version, rules in RULES.items() for kind, pattern in rules.items()}


#: Entries that one fold appends to; rows of a known address are dealt over as many keys.
BLOCK, SALTS = 128, 16


def _empty() -> Column:
    return F.array().cast("array<struct<start:bigint,k:int,kind:string,end:bigint>>")


def _let(value: Column, body) -> Column:
    """body(value) with the value worked out once, however often the body names it."""
    return F.transform(F.array(value), body)[0]


def _in_blocks(array: Column) -> Column:
    """The array cut into arrays of BLOCK entries, so that what folds append is copied within a block alone."""
    return F.transform(F.sequence(F.lit(0), F.greatest(F.ceil(F.size(array) / BLOCK) - 1, F.lit(0)).cast("int")), lambda b: F.slice(array, b * BLOCK + 1, F.lit(BLOCK)))


def _running(values: Column, step) -> Column:
    """What a fold from 0 has come to before each entry of an array of numbers, and at its end."""
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array(F.lit(0).cast("bigint")).alias("out"))

    def add(acc, x):
        at = step(acc.at, x).cast("bigint")
        return F.struct(at.alias("at"), F.concat(acc.out, F.array(at)).alias("out"))

    return F.aggregate(values, start, add, lambda a: a.out)


def _spans(text: Column, kind: str) -> Column:
    """Spans of the leftmost matches: the pieces between matches and the matches themselves give the places."""
    pattern = F.lit(KINDS[kind][1])
    rank = F.lit(list(KINDS).index(kind))
    gaps = F.transform(F.split(text, KINDS[kind][1], -1), F.length)
    hits = F.regexp_extract_all(text, pattern, F.lit(0))
    values = F.transform(F.regexp_extract_all(text, pattern, F.lit(2)), F.length) if kind == "assign" else None

    def zipped(hits):
        sizes = F.transform(hits, F.length)
        return F.arrays_zip(F.slice(gaps, F.lit(1), F.size(hits)).alias("gap"), sizes.alias("size"), (sizes if values is None else values).alias("value"))

    def step(acc, x):
        begin = acc.at + x["gap"]
        span = F.struct(begin.cast("bigint").alias("start"), rank.alias("k"), F.lit(kind).alias("kind"), (begin + x["size"]).cast("bigint").alias("end"))
        keep = x["value"] >= 6 if kind == "assign" else F.lit(True)
        return F.struct((begin + x["size"]).cast("bigint").alias("at"), F.when(keep, F.concat(acc.out, F.array(span))).otherwise(acc.out).alias("out"))

    def placed(blocks):
        sums = F.transform(blocks, lambda b: F.aggregate(b, F.lit(0).cast("bigint"), lambda a, x: a + x["gap"] + x["size"]))
        each = F.zip_with(blocks, F.slice(_running(sums, lambda at, x: at + x), F.lit(1), F.size(blocks)), lambda b, at: F.aggregate(b, F.struct(at.alias("at"), _empty().alias("out")), step, lambda a: a.out))
        return F.flatten(each)

    found = _let(hits, lambda h: _let(zipped(h), lambda z: _let(_in_blocks(z), placed)))
    return F.when(F.regexp_like(text, pattern), found).otherwise(_empty())


def redacted(text: Column, spans: Column, mark: str) -> Column:
    """The text with the mark in place of all that sorted spans cover; spans that overlap share one mark."""

    def cut(block, at0, end):
        def pieces(chunk):  # the text from at0 to end
            start = F.struct(at0.alias("at"), F.array().cast("array<string>").alias("out"))

            def step(acc, x):
                gap = F.substring(chunk, (acc.at - at0 + 1).cast("int"), F.greatest(x["start"] - acc.at, F.lit(0)).cast("int"))
                piece = F.when(x["start"] >= acc.at, F.concat(gap, F.lit(mark))).otherwise(F.lit(""))
                return F.struct(F.greatest(acc.at, x["end"]).alias("at"), F.concat(acc.out, F.array(piece)).alias("out"))

            return F.aggregate(block, start, step, lambda a: F.array_join(a.out, ""))

        return _let(F.substring(text, (at0 + 1).cast("int"), (end - at0).cast("int")), pieces)

    def joined(blocks):
        ends = F.transform(blocks, lambda b: F.array_max(F.transform(b, lambda x: x["end"])))

        def whole(at):
            numbered = F.sequence(F.lit(0), F.size(blocks) - 1)
            head = F.transform(numbered, lambda i: cut(blocks[i], at[i], at[i + 1]))
            return F.concat(F.array_join(head, ""), F.substring(text, (F.element_at(at, -1) + 1).cast("int"), F.length(text)))

        return _let(_running(ends, F.greatest), whole)

    return F.when(F.size(spans) > 0, _let(_in_blocks(spans), joined)).otherwise(text)


def scan(blobs: DataFrame, version: int) -> DataFrame:
    """(blob, version, spans) of blobs (blob, text) under one rule version."""
    found = F.concat(*(_spans(F.col("text"), kind) for kind in RULES[version]))
    return blobs.select("blob", F.lit(version).alias("version"), F.array_sort(found).alias("spans"))


def addressed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("text", F.coalesce("text", F.lit(""))).withColumn("blob", F.sha2("text", 256))


def scan_unseen(docs: DataFrame, ledger: DataFrame | None = None, versions=tuple(RULES)) -> DataFrame:
    """Ledger rows (blob, version, spans) for the pairs of blob and rule version that the ledger lacks."""
    blobs = addressed(docs).select("blob", "text")
    if ledger is not None:
        done = ledger.where(F.col("version").isin(*versions)).groupBy("blob").agg(F.collect_set("version").alias("done"))
        blobs = blobs.join(done, "blob", "left").where(F.size(F.array_except(F.array(*map(F.lit, versions)), F.coalesce("done", F.array().cast("array<int>")))) > 0)
    else:
        blobs = blobs.withColumn("done", F.array().cast("array<int>"))
    one = blobs.groupBy("blob").agg(F.first("text").alias("text"), F.first("done").alias("done"))
    parts = [scan(one.where(~F.array_contains(F.coalesce("done", F.array().cast("array<int>")), F.lit(v))), v) for v in versions] if ledger is not None else None
    if parts is None:  # nothing was seen: both versions in one pass over the blobs
        all_versions = F.array(*(F.struct(F.lit(v).alias("version"), F.array_sort(F.concat(*(_spans(F.col("text"), k) for k in RULES[v]))).alias("spans")) for v in versions))
        return one.select("blob", F.inline(all_versions))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def findings(docs: DataFrame, ledger: DataFrame, versions=tuple(RULES), *, text: bool = False) -> DataFrame:
    """docs with blob and spans: what the ledger has for the blob of each row. Rows with equal texts share findings.

    A blob that very many rows hold is dealt over SALTS keys: its findings, not its rows, are repeated. The text is
    not moved unless it is asked for.
    """
    known = ledger.where(F.col("version").isin(*versions)).where(F.size("spans") > 0)
    known = known.groupBy("blob").agg(F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans"))
    known = known.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(SALTS - 1).cast("bigint"))))
    held = addressed(docs).withColumn("salt", F.monotonically_increasing_id() % SALTS)
    return (held if text else held.drop("text")).join(known, ["blob", "salt"], "left").withColumn("spans", F.coalesce("spans", _empty())).drop("salt")


def redact_documents(docs: DataFrame, ledger: DataFrame, mark: str) -> DataFrame:
    """All rows of docs (text, n_chars, ...), each secret of the ledger replaced by the mark, n_chars counted anew.

    Null texts become empty. Repeated rows each get their row, an empty table gives an empty result, and very long
    texts are cut in one pass. All columns are kept, whatever their names; blob, spans and salt are taken by this.
    """
    out = findings(docs, ledger, text=True).withColumn("text", redacted(F.col("text"), F.col("spans"), mark))
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def _digest(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def secret_report(docs: DataFrame, ledger: DataFrame | None = None) -> DataFrame:
    """The digest of query op3.

    Null texts count as empty; an empty text has no spans. Repeated rows each get their row. An empty table gives an
    empty result, and other columns of docs are ignored. Very long texts are scanned whole, in time that grows little
    faster than the number of their matches.
    """
    docs = docs.select("doc_id", "text")
    new = scan_unseen(docs, ledger)
    found = findings(docs, new if ledger is None else ledger.unionByName(new))
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE_KINDS))

    def count(kind):
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = [count(kind) for kind in BASE_KINDS]
    return found.select("doc_id", *counts, F.sha2(_digest(base), 256).alias("base_sha256"), _digest(F.col("spans")).alias("spans"))
