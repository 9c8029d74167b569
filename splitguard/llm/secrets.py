"""Secret scan with corpus-wide ownership frequency, in DataFrame expressions only.

Candidates are found in the whole of every text. Their values are hashed and
counted over the corpus by distinct repositories and owners: a value seen under
many owners, or in very many repositories of a few, is a widely copied example; one seen
under few is owner-specific and looks live. Three kinds of candidates always count (assign, access, hex). A
fourth, long tokens of mixed letters and digits with no keyword beside them,
counts only where the ownership frequency says that it looks live; this is
what the corpus-wide step adds.

Spans are kind:start:end in code points, end exclusive. Defined results: a null
text is empty; a null source is an owner of its own; repeated rows are judged
each on its own; very long texts are scanned whole, and a text with very many spans takes time
in proportion to them; an empty table gives an empty result; other columns are ignored.

How positions come from built-in functions: a pattern is matched together with
the gap before it, anchored where the last match ended, so match lengths add up
to positions. Prefix sums go by blocks, which keeps a text with very many
matches from quadratic work.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from splitguard.functions.runtime import bind, join_by_key, reliable

# The patterns and least lengths of the result's contract.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"  # 16 characters or more of AKIA[A-Z0-9]+
HEX = r"[0-9a-f]{32,}"  # 32 characters or more of [0-9a-f]+
KINDS = ("assign", "access", "hex", "mixed")
LEAST_VALUE = 8

MIXED = r"[A-Za-z0-9]{20,}"
#: A value under more owners than this is a widely copied example.
LIVE_OWNERS = 2
#: So is one in more repositories than this, whoever owns them.
LIVE_REPOS = 25
_BLOCK = 256


def prefix_sums(lengths: Column) -> Column:
    """Inclusive prefix sums of an array of integers, by blocks."""

    def total(part: Column) -> Column:
        return F.aggregate(part, F.lit(0), lambda acc, x: acc + x)

    def upto(block: Column, base: Column) -> Column:
        return F.transform(
            F.sequence(F.lit(1), F.size(block)), lambda i: base + total(F.slice(block, 1, i))
        )

    def by_blocks(all_lengths: Column) -> Column:
        count = F.ceil(F.size(all_lengths) / _BLOCK).cast("int")
        blocks = F.transform(
            F.sequence(F.lit(0), count - 1),
            lambda b: F.slice(all_lengths, b * _BLOCK + 1, F.lit(_BLOCK)),
        )
        return bind(
            blocks,
            lambda bs: bind(
                F.transform(bs, total),
                lambda sums: F.flatten(
                    F.transform(bs, lambda b, i: upto(b, total(F.slice(sums, 1, i))))
                ),
            ),
        )

    return bind(
        lengths,
        lambda ls: F.when(F.size(ls) <= _BLOCK, upto(ls, F.lit(0))).otherwise(by_blocks(ls)),
    )


def spans_of(text: Column, pattern: str, kind: int, value_group: bool) -> Column:
    """array<struct<start, kind, end, value>> of all leftmost non-overlapping matches."""
    anchored = F.lit(rf"\G([\s\S]*?)({pattern})")
    empty = F.expr("cast(array() as array<struct<start:int,kind:int,end:int,value:string>>)")

    def build(found: Column) -> Column:
        return bind(
            prefix_sums(F.transform(found["whole"], F.char_length)),
            lambda ends: F.transform(
                F.arrays_zip(
                    ends.alias("end"), found["match"].alias("match"), found["value"].alias("value")
                ),
                lambda m: F.struct(
                    (m["end"] - F.char_length(m["match"])).alias("start"),
                    F.lit(kind).alias("kind"),
                    m["end"].cast("int").alias("end"),
                    m["value"].alias("value"),
                ),
            ),
        )

    def part(group: int) -> Column:
        return F.regexp_extract_all(text, anchored, F.lit(group))

    matched = F.struct(
        part(0).alias("whole"), part(2).alias("match"), part(3 if value_group else 2).alias("value")
    )
    return F.when(text.rlike(pattern), bind(matched, build)).otherwise(empty)


def candidates(text: Column) -> Column:
    """All candidates of a text in one array, before any of them is judged."""
    assign = F.filter(
        spans_of(text, ASSIGN, 0, True), lambda s: F.char_length(s["value"]) >= LEAST_VALUE
    )
    mixed = F.filter(
        spans_of(text, MIXED, 3, False),
        lambda s: s["value"].rlike("[a-z]") & s["value"].rlike("[A-Z]") & s["value"].rlike("[0-9]"),
    )
    return F.concat(assign, spans_of(text, ACCESS, 1, False), spans_of(text, HEX, 2, False), mixed)


def _uncovered(spans: DataFrame) -> DataFrame:
    """Rows (at, start, kind, end, ...) without the mixed spans that overlap a base span of their text.

    Sorted by start, the furthest end of the base spans so far and the nearest start of those
    to come tell it, so a text is gone through twice, whatever its number of spans.
    """
    text = Window.partitionBy("at")
    so_far = text.orderBy("start", "kind").rowsBetween(Window.unboundedPreceding, 0)
    to_come = text.orderBy(F.desc("start"), F.desc("kind")).rowsBetween(Window.unboundedPreceding, 0)
    is_base = F.col("kind") < 3
    marked = spans.select(
        "*",
        F.max(F.when(is_base, F.col("end"))).over(so_far).alias("reach"),
        F.min(F.when(is_base, F.col("start"))).over(to_come).alias("following"),
    )
    covered = (F.coalesce("reach", F.lit(0)) > F.col("start")) | (F.coalesce(F.col("following") < F.col("end"), F.lit(False)))
    return marked.where(is_base | ~covered).drop("reach", "following")


def _joined(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(
        F.transform(
            F.array_sort(spans),
            lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"], s["end"]),
        ),
        ",",
    )


def _digest_columns(spans: Column, *counts: Column) -> list[Column]:
    """Result columns from array<struct<start, kind, end>> of all kept spans."""

    def count(kind: int) -> Column:
        return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")

    base = F.filter(spans, lambda s: s["kind"] < 3)
    return [
        F.col("doc_id"),
        count(0).alias("n_assign"),
        count(1).alias("n_access"),
        count(2).alias("n_hex"),
        F.sha2(_joined(base), 256).alias("base_sha256"),
        _joined(spans).alias("spans"),
        *[c.cast("long").alias(name) for c, name in zip(counts, ("n_live", "n_copied", "most_owners", "most_repos"))],
    ]


def ownership(found: DataFrame) -> DataFrame:
    """(digest, n_repos, n_owners, n) from rows (digest, repo, owner), in three combined steps."""
    per_repo = found.groupBy("digest", "owner", "repo").agg(F.count(F.lit(1)).alias("n"))
    per_owner = per_repo.groupBy("digest", "owner").agg(
        F.count(F.lit(1)).alias("repos"), F.sum("n").alias("rows")
    )
    return per_owner.groupBy("digest").agg(
        F.sum("repos").alias("n_repos"), F.count(F.lit(1)).alias("n_owners"), F.sum("rows").alias("n")
    )


def judged_spans(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    repo_col: str = "source",
    live_owners: int = LIVE_OWNERS,
    live_repos: int = LIVE_REPOS,
) -> tuple[DataFrame, DataFrame]:
    """(rows, spans): rows (at, doc_id, n) for every input row, spans (at, start, kind, end, live, ...).

    The owner is the part of the repository's name before the first slash.
    """
    repo = F.col(repo_col).cast("string")
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        repo.alias("repo"),
        F.substring_index(repo, "/", 1).alias("owner"),
        candidates(F.coalesce(F.col(text_col), F.lit(""))).alias("found"),
    )
    rows = reliable(rows.withColumn("at", F.monotonically_increasing_id()))
    found = rows.select("at", "doc_id", "repo", "owner", F.explode("found").alias("s")).select(
        "at", "doc_id", "repo", "owner", "s.start", "s.kind", "s.end",
        F.sha2("s.value", 256).alias("digest"),
    )
    found = reliable(_uncovered(found))
    owned = reliable(ownership(found))
    live = (F.col("n_owners") <= live_owners) & (F.col("n_repos") <= live_repos)
    return rows, join_by_key(found, owned, ["digest"]).withColumn("live", live)


def secret_digests(docs: DataFrame, **columns: str) -> DataFrame:
    """One row a document: counts by kind, digest of the base spans, all kept spans, how many of
    them look live or copied, and the most owners and repositories that any of its values has."""
    rows, spans = judged_spans(docs, **columns)
    kept = (F.col("kind") < 3) | F.col("live")
    by_row = spans.groupBy("at", "doc_id").agg(  # bounded by one document
        F.collect_list(F.when(kept, F.struct("start", "kind", "end"))).alias("spans"),
        F.count_if(F.col("live")).alias("live"),
        F.count_if(kept & ~F.col("live")).alias("copied"),
        F.max("n_owners").alias("owners"),
        F.max("n_repos").alias("repos"),
    )
    found = by_row.select(*_digest_columns(*map(F.col, ("spans", "live", "copied", "owners", "repos"))))
    none = F.expr("cast(array() as array<struct<start:int,kind:int,end:int>>)")
    bare = rows.where(F.size("found") == 0).select(*_digest_columns(none, *[F.lit(0)] * 4))
    return bare.unionByName(found)
