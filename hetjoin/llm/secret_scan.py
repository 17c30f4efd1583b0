"""Secret scan with corpus-wide ownership: who else has this value tells an example from a live credential.

All of it is DataFrame expressions. Each kind's matches and the gaps between them give the
places of the matches. Hashes of the values are counted by distinct repositories, then by
owner, then over owners, so a value that everyone copies costs one row per owner in the last
step. A value that many owners have, or many repositories, is a widely copied example; the
others look live. The owner is the column ``source``; where no column names the repository,
each document is one of its owner's repositories.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import written

# The base patterns. Their length limits apply to whole matches, after matching.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"(AKIA[A-Z0-9]{12,})"
HEX = r"([0-9a-f]{32,})"
# Long mixed strings, taken up only if few owners have them.
MIXED = r"([A-Za-z0-9_-]{20,})"
KINDS = [("assign", ASSIGN, 2, 8), ("access", ACCESS, 1, 16), ("hex", HEX, 1, 32), ("owned", MIXED, 1, 20)]
BASE = 3
MAX_OWNERS, MAX_REPOSITORIES = 2, 20


def _found(text: Column, number: int) -> Column:
    """Matches of one kind: its number, place in order, characters since the last match, own length, value's hash and fitness."""
    _, pattern, group, least = KINDS[number]
    pat = F.lit(pattern)
    entry = F.arrays_zip(F.regexp_extract_all(text, pat, F.lit(0)).alias("whole"), F.regexp_extract_all(text, pat, F.lit(group)).alias("value"), F.split(text, pattern, -1).alias("gap"))
    fit = lambda v: (F.length(v) >= least) & ((v.rlike("[0-9]") & v.rlike("[a-z]") & v.rlike("[A-Z]")) if number == BASE else F.lit(True))
    rows = F.transform(
        F.filter(entry, lambda x: x["whole"].isNotNull()),
        lambda x, i: F.struct(F.lit(number).alias("kind"), i.alias("nth"), F.length(x["gap"]).alias("gap"), F.length(x["whole"]).alias("size"), F.xxhash64(x["value"]).alias("hash"), fit(x["value"]).alias("fit")),
    )
    none = F.array().cast("array<struct<kind:int,nth:int,gap:int,size:int,hash:bigint,fit:boolean>>")
    return F.when(text.rlike(pattern), rows).otherwise(none)


def candidates(docs: DataFrame, owner: str = "source", repository: str = "doc_id") -> DataFrame:
    """A written row for every document: ``_row``, doc_id, owner, repository and all matches, but not its text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    named = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("")) if c in docs.columns else F.lit("")
    chosen = docs.select(F.monotonically_increasing_id().alias("_row"), "doc_id", named(owner).alias("_owner"), named(repository).alias("_repository"), F.xxhash64(text).alias("_text"), F.concat(*[_found(text, k) for k in range(len(KINDS))]).alias("_found"))
    return written(chosen, "secret-candidates")


def placed(found: DataFrame) -> DataFrame:
    """One row per fitting match: _row, _owner, _repository, kind, start, end (code points, end exclusive) and hash."""
    w = Window.partitionBy("_row", "kind").orderBy("nth")
    rows = found.where(F.size("_found") > 0).select("_row", "_owner", "_repository", F.inline("_found"))
    return rows.withColumn("end", F.sum(F.col("gap") + F.col("size")).over(w)).where("fit").select("_row", "_owner", "_repository", "kind", (F.col("end") - F.col("size")).alias("start"), "end", "hash")


def ownership(matches: DataFrame) -> DataFrame:
    """hash, n_copies, n_repositories, n_owners over the whole corpus; a repository is one of its owner's."""
    by_repository = matches.groupBy("hash", "_owner", "_repository").agg(F.count("*").alias("_n"))
    by_owner = by_repository.groupBy("hash", "_owner").agg(F.sum("_n").alias("_n"), F.count("*").alias("_r"))
    return by_owner.groupBy("hash").agg(F.sum("_n").alias("n_copies"), F.sum("_r").alias("n_repositories"), F.count("*").alias("n_owners"))


def judged(found: DataFrame, max_owners: int = MAX_OWNERS, max_repositories: int = MAX_REPOSITORIES) -> DataFrame:
    """Per document with matches: ``spans`` sorted by start and kind, each with kind, start, end and ``live``.

    Base matches all stay. A long mixed string is added where its value is live and no base
    match overlaps it. ``live``: at most so many owners and repositories have the value.
    """
    matches = written(placed(found), "secret-matches")
    live = (F.col("n_owners") <= max_owners) & (F.col("n_repositories") <= max_repositories)
    seen = matches.join(ownership(matches).select("hash", live.alias("live")), "hash").where((F.col("kind") < BASE) | F.col("live"))
    base = F.col("kind") < BASE
    # Running extremes from either end: the base span that reaches farthest, and the next that begins.
    reach = F.max(F.when(base, F.col("end"))).over(Window.partitionBy("_row").orderBy("start"))
    following = F.min(F.when(base, F.col("start"))).over(Window.partitionBy("_row").orderBy(F.desc("start")))
    free = ~F.coalesce(F.col("_reach") > F.col("start"), F.lit(False)) & ~F.coalesce(F.col("_next") < F.col("end"), F.lit(False))
    kept = seen.withColumn("_reach", reach).withColumn("_next", following).where(base | free)
    return kept.groupBy("_row").agg(F.sort_array(F.collect_list(F.struct("start", "kind", "end", "live"))).alias("spans"))


def _told(spans: Column) -> Column:
    names = F.array(*[F.lit(k[0]) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"], x["end"])), ",")


def scan(docs: DataFrame, owner: str = "source", repository: str = "doc_id", max_owners: int = MAX_OWNERS, max_repositories: int = MAX_REPOSITORIES) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_owned, n_live, n_example for every document.

    Null and empty texts have no spans; null owners count as one owner without a name; rows that
    repeat an id come out as often. An empty table gives no rows, other columns of the input play
    no part. ``n_live`` counts base and added spans whose value looks live, ``n_example`` the base
    spans whose value is widely copied.
    """
    found = candidates(docs, owner, repository)
    rows = found.select("_row", "doc_id").join(judged(found, max_owners, max_repositories), "_row", "left")
    spans = F.coalesce(F.col("spans"), F.array().cast("array<struct<start:bigint,kind:int,end:bigint,live:boolean>>"))
    count = lambda test: F.size(F.filter("_s", test)).cast("long")

    def of_kind(number: int):
        # A second parameter of the lambda would be the index of the element.
        return lambda x: x["kind"] == number

    return rows.withColumn("_s", spans).select(
        "doc_id",
        *[count(of_kind(k)).alias(f"n_{KINDS[k][0]}") for k in range(BASE)],
        F.sha2(_told(F.filter("_s", lambda x: x["kind"] < BASE)), 256).alias("base_sha256"),
        _told(F.col("_s")).alias("spans"),
        count(of_kind(BASE)).alias("n_owned"),
        count(lambda x: x["live"]).alias("n_live"),
        count(lambda x: ~x["live"]).alias("n_example"),
    )


def redact(docs: DataFrame, owner: str = "source", repository: str = "doc_id", mask: str = "[SECRET]") -> DataFrame:
    """The documents with their live spans masked; ``n_chars``, where present, follows. No row goes.

    Spans come back by id and text, so equal rows stay equal and repeated ids are no problem.
    Overlapping spans become one mask.
    """
    found = candidates(docs, owner, repository)
    live = judged(found).select("_row", F.filter("spans", lambda x: x["live"]).alias("_spans")).where(F.size("_spans") > 0)
    keyed = found.select("_row", "doc_id", "_text").join(live, "_row").groupBy(F.col("doc_id").alias("_id"), "_text").agg(F.first("_spans").alias("_spans"))
    text = F.coalesce(F.col("text"), F.lit(""))
    begin = F.struct(F.lit("").alias("out"), F.lit(0).cast("bigint").alias("at"))

    def step(acc, s):
        new = F.concat(acc["out"], F.col("text").substr((acc["at"] + 1).cast("int"), F.greatest(s["start"] - acc["at"], F.lit(0)).cast("int")), F.when(s["start"] >= acc["at"], F.lit(mask)).otherwise(F.lit("")))
        return F.struct(new.alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))

    masked = F.aggregate("_spans", begin, step, lambda acc: F.concat(acc["out"], F.col("text").substr((acc["at"] + 1).cast("int"), F.length("text"))))
    joined = docs.join(keyed, docs["doc_id"].eqNullSafe(keyed["_id"]) & (F.xxhash64(text) == keyed["_text"]), "left")
    new_text = F.when(F.col("_spans").isNull(), F.col("text")).otherwise(masked)
    out = joined.withColumn("_new", new_text)
    return out.select(*[F.col("_new").alias("text") if c == "text" else F.length("_new").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else docs[c] for c in docs.columns])
