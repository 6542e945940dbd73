"""Exact deduplication by a tree-merge of sorted digest runs, in DataFrame operations only.

Every document becomes one entry (digest, length, check, id) of a *run*; there are fan_in ** depth runs. In each
of depth rounds groups of ``fan_in`` runs exchange entries along one digit of their number, as in a binomial
tree: the group's entries are cut into slices of the digests' range, one slice goes to each of the group's tasks,
and there it is merged in digest order by a sort and a streaming (sort) aggregate that keeps one verified
identifier and the number of copies of each digest. So the number of tasks stays the same in all rounds, an entry
meets at most ``fan_in`` others of its digest in a round, and after the last one every digest has one entry. The
tree is then walked back down: a merged entry answers the at most ``fan_in`` entries it came from. A text which a
third of all rows share never meets in one task, neither on the way up nor on the way down.

Digests are SHA-256 of the normalised text; an identifier is only retained as verified if the length and an
independent 64-bit hash agree as well.

Defined results: a null text counts as empty; rows with a null id take part in their group's size, never
become ``keep_id`` while another id exists and are kept only if the whole group has no id; repeated ids with
equal texts share one fate in ``exact_groups``, while ``keep_one`` returns one row of each text; an empty table gives
an empty result; further columns are not read by ``exact_groups`` and kept by ``keep_one``, whatever they are called.
"""

from __future__ import annotations

import string

from pyspark.sql import DataFrame, functions as F

from .common import cut, require_columns, shuffle_width

UPPER, LOWER = string.ascii_uppercase, string.ascii_lowercase


def normalised(text) -> F.Column:
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def _shape(width: int, most: int) -> tuple[int, int]:
    """(depth, fan_in): the fewest rounds of ``most`` runs each, and the smallest fan_in that still makes ``width`` runs.

    Every round has as many tasks as there are runs, so more of these than the session's shuffles have would only cost files."""
    depth = 1
    while most**depth < width:
        depth += 1
    fan_in = 2
    while fan_in**depth < width:
        fan_in += 1
    return depth, fan_in


ENTRY = ["digest", "length", "check"]


def merge_runs(runs: DataFrame, level: int, fan_in: int, units: int, keep: str) -> DataFrame:
    """One round: (run, digest, length, check, best, copies) of the runs one level up, with their slice's number (unit).

    best is a struct, for which Spark aggregates in sort order: the rows of a unit are sorted once and merged as a stream."""
    parent = F.floor(F.col("run") / fan_in).cast("int")
    slices = fan_in**level
    place = F.conv(F.hex(F.substring("digest", 1, 4)), 16, 10).cast("long") * slices / F.lit(1 << 32)
    dealt = runs.withColumn("run", parent).withColumn("unit", F.col("run") * slices + F.floor(place).cast("int"))
    pick = F.max if keep == "largest" else F.min
    return dealt.repartition(units, "unit").groupBy("unit", "run", *ENTRY).agg(pick("best").alias("best"), F.sum("copies").alias("copies"))


def merge_tree(entries: DataFrame, keep: str, fan_in: int = 8) -> DataFrame:
    """entries (id, digest, length, check) with keep_id and copies of their group, by rounds of merges up and answers down.

    fan_in: how many runs are merged at once at most."""
    depth, fan_in = _shape(shuffle_width(entries.sparkSession), fan_in)
    units = fan_in**depth
    # Dealt in turn, so that no id fills a run; what is written holds from here on, also when tasks are repeated.
    entries = cut(entries.withColumn("run", F.pmod(F.monotonically_increasing_id() + F.floor(F.monotonically_increasing_id() / F.lit(1 << 33)), F.lit(units)).cast("int")), "digest-runs")
    known = F.col("id").isNotNull() if keep == "largest" else F.col("id").isNull()  # a null never wins
    levels = [entries.select("run", *ENTRY, F.struct(known.alias("known"), F.col("id").alias("id")).alias("best"), F.lit(1).cast("long").alias("copies"))]
    for level in range(1, depth + 1):
        levels.append(merge_runs(levels[-1], level, fan_in, units, keep).drop("unit"))
    answer = levels[-1].select("run", *ENTRY, F.col("best.id").alias("keep_id"), "copies")
    for level in reversed(levels[1:-1]):
        below = level.select(F.col("run").alias("child"), F.floor(F.col("run") / fan_in).cast("int").alias("run"), *ENTRY)
        answer = below.join(answer, ["run", *ENTRY]).drop("run").withColumnRenamed("child", "run")
    asked = entries.withColumn("leaf", F.col("run")).withColumn("run", F.floor(F.col("run") / fan_in).cast("int"))
    return asked.join(answer, ["run", *ENTRY]).drop("run", "leaf")


def digests(text) -> list[F.Column]:
    return [F.unhex(F.sha2(text, 256)).alias("digest"), F.octet_length(text).alias("length"), F.xxhash64(text).alias("check")]


def exact_groups(docs: DataFrame, keep: str = "largest", fan_in: int = 8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of ``docs``: id, keep_id, group_size, kept, text_sha256. ``keep``: 'largest' or 'smallest' id."""
    require_columns(docs, id_col, text_col)
    if keep not in ("largest", "smallest"):
        raise ValueError("keep is 'largest' or 'smallest'")
    entries = docs.select(F.col(id_col).alias("id"), *digests(normalised(F.col(text_col))))
    return merge_tree(entries, keep, fan_in).select(
        F.col("id").alias(id_col),
        "keep_id",
        F.col("copies").alias("group_size"),
        F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def keep_one(docs: DataFrame, keep: str = "largest", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of ``docs`` for each text, with all its columns: of the id that stays, whatever else that id is used for."""
    name = F.coalesce(F.concat(F.lit("#"), F.col(id_col).cast("string")), F.lit(""))
    stay = exact_groups(docs, keep, id_col=id_col, text_col=text_col).filter("kept").select(name.alias("__id"), F.unhex("text_sha256").alias("__text")).distinct()
    packed = docs.select(F.struct("*").alias("row"), name.alias("__id"), F.unhex(F.sha2(normalised(F.col(text_col)), 256)).alias("__text"))
    # Rows alike in id and text are merged before they travel; what is left has the join's keys.
    single = packed.groupBy("__id", "__text").agg(F.first("row").alias("row"))
    return single.join(stay, ["__id", "__text"], "left_semi").select("row.*")


ORACLE = """
WITH n AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT n.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, n.doc_id IS NOT DISTINCT FROM g.keep_id AS kept, sha256(n.t) AS text_sha256
FROM n JOIN g ON n.t = g.t
"""
