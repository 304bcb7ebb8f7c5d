"""Secret scan with corpus-wide ownership frequency, in DataFrame functions only.

Base spans come from three patterns.  The method looks at every opaque value -
the value of a base span, and any long token that mixes letters and digits - by
its hash over the whole corpus: in how many distinct repositories and of how
many distinct owners it occurs.  Values that several owners hold, or many
repositories of one, are copied examples (documentation keys, digests of common
files); values of one owner in few repositories look live.  Opaque tokens outside
the base patterns count as secrets only if they look live; base spans stay
whatever their owners.

Texts are searched once: what is found is written to the shared folder, and the
frequencies and the decision read it there.  Rows without any candidate are not
shuffled.

Positions come from cutting a text at a pattern's matches: the lengths of the
pieces and of the matches add up to code-point offsets.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .textblocks import materialize

#: Fixed patterns of the base spans: kind, pattern, group that carries the value, fewest characters of that group.
BASE_PATTERNS = (
    ("assign", "([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 8),
    ("access", "AKIA[A-Z0-9]+", 0, 16),
    ("hex", "[0-9a-f]+", 0, 32),
)
#: Tokens that the method adds: at least so many characters of a credential's alphabet, with letters of both cases and digits.
OPAQUE_PATTERN = "[A-Za-z0-9+/_-]{24,}"


def _longer(pattern: str, least: int) -> str:
    """For a pattern that is one run of a class: runs below the least length need not be told apart at all."""
    return pattern.removesuffix("+") + "{%d,}" % (least - 4 if pattern.startswith("AKIA") else least)


#: Matches whose places are added up in one go; sums of such runs are added up over them.
_RUN = 128


def _running(pairs: Column) -> Column:
    """From (gap before, length) of each match: (start, end) of each. The last gap has no match."""
    nothing = F.array().cast("array<struct<start:int,end:int>>")

    def step(s: Column, x: Column) -> Column:
        start = s["at"] + x["g"]
        end = start + F.coalesce(x["m"], F.lit(0))
        return F.struct(end.alias("at"), F.when(x["m"].isNull(), s["out"]).otherwise(F.concat(s["out"], F.array(F.struct(start.alias("start"), end.alias("end"))))).alias("out"))

    runs = F.transform(F.sequence(F.lit(0), F.floor((F.size(pairs) - 1) / _RUN).cast("int")), lambda i: F.slice(pairs, i * _RUN + 1, F.lit(_RUN)))
    local = F.transform(runs, lambda r: F.aggregate(r, F.struct(F.lit(0).alias("at"), nothing.alias("out")), step))
    base = F.aggregate(local, F.array(F.lit(0)), lambda s, x: F.concat(s, F.array(F.element_at(s, -1) + x["at"])))
    moved = F.zip_with(local, base, lambda r, b: F.transform(r["out"], lambda p: F.struct((p["start"] + b).alias("start"), (p["end"] + b).alias("end"))))
    return F.flatten(F.filter(moved, lambda r: r.isNotNull()))


def _spans(text: Column, kind: str, pattern: str, group: int, least: int) -> Column:
    """array<struct<start, end, value, kind>> of a pattern's leftmost matches whose value is long enough; code points, end exclusive."""
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.transform(F.split(text, pattern, -1), F.length)
    starts = _running(F.arrays_zip(gaps.alias("g"), F.transform(whole, F.length).alias("m")))
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else whole
    found = F.zip_with(starts, values, lambda p, v: F.struct(p["start"].alias("start"), p["end"].alias("end"), v.alias("value"), F.lit(kind).alias("kind")))
    none = F.array().cast("array<struct<start:int,end:int,value:string,kind:string>>")
    return F.when(text.rlike(pattern), F.filter(found, lambda s: F.length(s["value"]) >= least)).otherwise(none)


def _opaque(spans: Column) -> Column:
    mixed = lambda v: v.rlike("[A-Z]") & v.rlike("[a-z]") & v.rlike("[0-9]")
    return F.filter(spans, lambda s: mixed(s["value"]))


def _told(spans: Column) -> Column:
    """kind:start:end of spans in order of start, then of kind as listed."""
    order = {k: i for i, (k, *_) in enumerate(BASE_PATTERNS)} | {"opaque": len(BASE_PATTERNS)}
    rank = lambda k: reduce(lambda c, x: c.when(k == x[0], x[1]), list(order.items())[1:], F.when(k == "assign", 0))
    ranked = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), rank(s["kind"]).alias("rank"), s["end"].alias("end"), s["kind"].alias("kind"))))
    return F.array_join(F.transform(ranked, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", repo_cols: tuple[str, ...] = ("source", "lang"), owner_col: str = "source") -> DataFrame:
    """(id, owner, repo, base, opaque) of every row; base and opaque are arrays of spans."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).alias("id"), F.col(owner_col).cast("string").alias("owner"), F.array(*(F.col(c).cast("string") for c in repo_cols)).alias("repo"), text.alias("text"))
    kinds = [_spans(F.col("text"), k, p if g else _longer(p, n), g, n) for k, p, g, n in BASE_PATTERNS]
    return rows.withColumn("base", F.concat(*kinds)).withColumn("opaque", _opaque(_spans(F.col("text"), "opaque", OPAQUE_PATTERN, 0, 24)))


_SOME = "size(base) > 0 OR size(opaque) > 0"


def _values() -> Column:
    """Hashes of a row's distinct candidate values."""
    return F.array_distinct(F.transform(F.concat("base", "opaque"), lambda s: F.xxhash64(s["value"])))


def ownership(found: DataFrame) -> DataFrame:
    """(value_hash, n_owners, n_repos, n_places) of every candidate value over the corpus.

    Distinct (value, owner, repository) are made first, so a value that a third of all documents
    hold is summed before it moves. A null owner is an owner of its own, and so are null parts of a repository.
    """
    each = found.filter(_SOME).select(F.explode(_values()).alias("value_hash"), "owner", "repo")
    return (
        each.groupBy("value_hash", "owner", "repo").agg(F.count("*").alias("n"))
        .groupBy("value_hash", "owner").agg(F.count("*").alias("repos"), F.sum("n").alias("n"))
        .groupBy("value_hash").agg(F.count("*").alias("n_owners"), F.sum("repos").alias("n_repos"), F.sum("n").alias("n_places"))
    )


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", repo_cols: tuple[str, ...] = ("source", "lang"), owner_col: str = "source", live_owners: int = 1, live_repos: int = 2, keep_text: bool = False) -> DataFrame:
    """(id, n_assign, n_access, n_hex, base, spans, n_live, n_shared[, text]) of every row.

    base, spans: arrays of (start, end, value, kind); spans are the base ones and the opaque
    tokens that look live: of at most `live_owners` owners and `live_repos` repositories.
    n_live, n_shared: values of the row's base and opaque spans that look live, and the others.
    Null and empty texts have no spans; a null owner counts as one owner; rows that repeat a
    value count once an owner.  Repeated rows give repeated results, an empty table an empty
    one.  Columns beside those named are not read.
    """
    # documents by a key that recomputation gives alike
    key = F.xxhash64(F.col("id").cast("string"), F.isnull("id"), F.col("owner"), F.isnull("owner"), F.to_json("repo"), F.xxhash64("text"))
    kept = ["text"] if keep_text else []
    found = materialize(candidates(docs, id_col, text_col, repo_cols, owner_col).withColumn("row_key", key).select("row_key", "id", "owner", "repo", "base", "opaque", *kept), "candidates")
    live = ownership(found).filter((F.col("n_owners") <= live_owners) & (F.col("n_repos") <= live_repos)).select("value_hash")
    some = found.filter(_SOME)
    # one row a document and value
    of_row = some.select("row_key", F.explode(_values()).alias("value_hash")).join(live, "value_hash").groupBy("row_key").agg(F.collect_set("value_hash").alias("live"))
    none = F.array().cast("array<bigint>")
    judged = some.drop("owner", "repo").join(of_row, "row_key", "left").withColumn("live", F.coalesce("live", none))
    rows = judged.unionByName(found.filter(f"NOT ({_SOME})").drop("owner", "repo").withColumn("live", none))
    added = F.filter("opaque", lambda s: F.array_contains("live", F.xxhash64(s["value"])))
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long")
    n_live = F.size("live").cast("long")
    return rows.select("id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"), "base", F.concat("base", added).alias("spans"), n_live.alias("n_live"), (F.size(_values()).cast("long") - n_live).alias("n_shared"), *kept)


def told(spans: Column) -> Column:
    """Spans as text: kind:start:end, comma-joined in order."""
    return _told(spans)


def redact(text: Column, spans: Column, mask: str = "[SECRET]") -> Column:
    """The text with each maximal run of overlapping spans replaced by the mask."""
    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"))))
    done = F.aggregate(
        ordered,
        F.struct(F.lit(0).alias("at"), F.lit("").alias("out")),
        lambda s, x: F.when(x["end"] <= s["at"], s).otherwise(
            F.struct(x["end"].alias("at"), F.when(x["start"] < s["at"], s["out"]).otherwise(F.concat(s["out"], F.substring(text, s["at"] + 1, x["start"] - s["at"]), F.lit(mask))).alias("out"))
        ),
        lambda s: F.concat(s["out"], F.substring(text, s["at"] + 1, F.length(text))),
    )
    return F.when(F.size(spans) > 0, done).otherwise(text)
