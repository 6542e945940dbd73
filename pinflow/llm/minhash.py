"""Near-duplicate detection with bottom-k sketches of one hash function.

1. Every text becomes its set of five-word shingles; the k smallest hashes of the set are its sketch. Equal
   sets collapse to their smallest id by a tree-merge, so copies never meet again.
2. Inverted lists hold the retained values. Texts as similar as asked share at least ``need`` retained values,
   so it is enough to list the rarest ``size - need + 1`` values of each sketch: passages that very many texts
   share drop out unless they make up most of a text.
3. Lists yield pairs of a *hub* with the other members. First each text meets the one hub that it shares most
   lists with. Lists that then hold one component are done. Of the others, those of up to ``CROWD`` members
   test all pairs between components; larger ones are first rebuilt from the full sets of their members: the
   rarest shingles of each set, without those that no other member has, which also bounds what a text can
   share and takes out texts that are too far from all others. Members of what is still crowded become
   hubs by turns, those of small components first and more in each round, and leave the list
   afterwards. All pairs that could still join two components are tested in the end, but a group of mutual
   copies costs one star.
4. Pairs pass a size test and the estimate from the sketch of their union, then full sets decide exactly.
5. Components come from star rounds over the confirmed links.

A row of a list carries a sketch of ``WIDE`` values at most, so lists grow in proportion to the texts.

The only chance is in 2 and 4: a pair of similarity s >= 0.75 is missed if far fewer of the smallest values of its
union are shared than that share: under 10 of 32 for the lists, 28 of 64 for the estimate, 5.6 standard deviations
elsewhere. Each is below 1e-7 at s = 0.75 and falls fast above; sets of up to 24 shingles lie whole in their
sketches and are never missed.

Defined results: null and empty texts and texts without words have the empty set, n_shingles 0, and stay
alone; rows that repeat an id with the same text share one fate; where an id has several texts, each is judged on
its own and component_id is the smallest id among the rows reached; rows with a null id are passed through unlinked;
an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from pinflow.operators.shape import dense_ids

from .common import cut, discard, release, require_columns, shuffle_width, trimmed
from .exact_dedup import merge_tree
from .graph import components
from .shingles import chunks, confirmed_sets, shingle_sets

SKETCH = 64  # values kept of each set
LISTED = 32  # of these, the values that make lists
NEED = 10  # of LISTED
LIKELY = 28  # of SKETCH
PERCENT = 75
SALTS = 256
CROWD = 64
WIDE = 512  # values kept of a crowded list's members
HUBS = 512  # members of a crowded list that meet all others in its first round
CHUNK = 1024  # members of a list that are met at once
TOLD = 64  # lists of a text by which it is settled where a pair is told
DENSE = 1 << 20  # cells up to which a list's sketches are compared as one matrix


def sketches(docs: DataFrame, id_col: str, text_col: str, k: int = SKETCH) -> DataFrame:
    """(doc_id, n_shingles, set_key, sketch, text_key) of every row."""

    def run(batches):
        for batch in batches:
            texts = [t or b"" for t in batch.column(1).to_pylist()]
            for a, z in chunks(texts):
                sets = shingle_sets(texts[a:z])
                keys = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets]
                heads = [s[:k] for s in sets]
                ends = np.concatenate([[0], np.cumsum([len(h) for h in heads])]).astype(np.int32)
                values = np.concatenate(heads).astype(np.int64)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, z - a), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys, pa.binary()), pa.ListArray.from_arrays(pa.array(ends), pa.array(values)), batch.column(2).slice(a, z - a)],
                    ["doc_id", "n_shingles", "set_key", "sketch", "text_key"],
                )

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").cast("binary"), text_key(F.col(text_col)))
    return narrow.mapInArrow(trimmed(run), "doc_id bigint, n_shingles bigint, set_key binary, sketch array<bigint>, text_key binary")


def text_key(text) -> F.Column:
    return F.unhex(F.sha2(F.coalesce(text.cast("string"), F.lit("")), 256)).alias("text_key")


def renamed(sets: DataFrame) -> DataFrame | None:
    """(doc_id, text_key, node) of the texts of an id but its first one: ids that no row has. None if no id has two texts."""
    firsts = sets.groupBy("doc_id").agg(F.min("text_key").alias("lo"), F.max("text_key").alias("hi")).filter("doc_id is not null and lo <> hi")
    if firsts.isEmpty():
        return None
    more = sets.join(firsts, "doc_id").filter("text_key <> lo").select("doc_id", "text_key").distinct()
    ends = sets.agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).first()  # one row
    base = F.lit(ends["hi"] + 1) if ends["hi"] < 1 << 62 else F.lit(ends["lo"] - (1 << 48))
    return cut(dense_ids(cut(more, "texts-of-ids"), F.col("doc_id"), F.col("text_key"), name="at").select("doc_id", "text_key", (F.col("at") + base).alias("node")), "renamed")


def with_nodes(rows: DataFrame, names: DataFrame | None) -> DataFrame:
    """rows (doc_id, text_key, ...) with node: the id, or what stands for it where an id has several texts."""
    if names is None:
        return rows.withColumn("node", F.col("doc_id"))
    return rows.join(names, ["doc_id", "text_key"], "left").withColumn("node", F.coalesce("node", "doc_id"))


def required_overlap(n, k: int, percent: int, need: int):
    """How many retained values a text of n shingles shares with any text as similar as asked."""
    return F.when(n * 100 <= F.lit(k * percent), F.ceil(n * percent / 100)).otherwise(F.lit(need)).cast("int")


def inverted_lists(reps: DataFrame, k: int, percent: int, need: int) -> DataFrame:
    """(value, doc_id, n, s, share): the rarest retained values of every sketch that another sketch retains too.

    n: size of the set; s: at most so many of its shingles are in another set; share: the part of the sketch that others retain."""
    values = F.slice("sketch", 1, k)
    entries = reps.select("doc_id", F.col("n_shingles").alias("n"), F.size(values).alias("size"), F.explode(values).alias("value"))
    shared = entries.groupBy("value").agg(F.count("*").alias("df")).filter("df > 1")
    ranked = entries.join(shared, "value").groupBy("doc_id", "n", "size").agg(F.sort_array(F.collect_list(F.struct("df", "value"))).alias("by_df"))
    # Values of one text only come first in the order: they use up the prefix without making a list.
    room = F.greatest(F.lit(0), F.size("by_df") - required_overlap(F.col("n"), k, percent, need) + 1)
    share = F.size("by_df") / F.col("size")
    listed = ranked.select("doc_id", "n", F.col("n").alias("s"), share.alias("share"), F.explode(F.slice("by_df", F.lit(1), room)).alias("e"))
    return cut(listed.select(F.col("e.value").alias("value"), "doc_id", "n", "s", "share"), "inverted-lists")


ENTRY = np.dtype([("value", "<i8"), ("doc", "<i8"), ("n", "<i8"), ("df", "<i8")])
PARCEL = "bucket int, data binary"


def _parcels(rows: np.ndarray, bucket: np.ndarray):
    """Rows packed by bucket: shingles of full sets travel as arrays, not as rows."""
    order = np.argsort(bucket, kind="stable")
    rows, bucket = rows[order], bucket[order]
    edges = np.flatnonzero(np.diff(bucket)) + 1
    firsts = np.concatenate([[0], edges]).astype(np.int64) if len(rows) else []
    return pa.RecordBatch.from_arrays([pa.array([int(bucket[i]) for i in firsts], pa.int32()), pa.array([p.tobytes() for p in np.split(rows, edges)] if len(rows) else [], pa.binary())], ["bucket", "data"])


def _gathered(batches):
    """(bucket, its entries) in bucket order."""
    current, held = None, []
    for batch in batches:
        for bucket, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            if bucket != current and held:
                yield np.concatenate(held)
                held = []
            current = bucket
            held.append(np.frombuffer(data, dtype=ENTRY))
    if held:
        yield np.concatenate(held)


def _deal(width: int):
    def run(batches):
        for batch in batches:
            sets = batch.column(1)
            sizes = sets.value_lengths().to_numpy()
            rows = np.zeros(int(sizes.sum()), dtype=ENTRY)
            rows["value"] = sets.flatten().to_numpy()
            rows["doc"], rows["n"] = np.repeat(batch.column(0).to_numpy(), sizes), np.repeat(sizes, sizes)
            yield _parcels(rows, rows["value"] % width)

    return run


def _count_shared(width: int):
    """Entries whose value is in two sets at least, with that number, to their documents' buckets."""

    def run(batches):
        for rows in _gathered(batches):
            rows = rows[np.argsort(rows["value"], kind="stable")]
            firsts = np.flatnonzero(np.concatenate([[True], rows["value"][1:] != rows["value"][:-1]]))
            sizes = np.diff(np.concatenate([firsts, [len(rows)]]))
            rows["df"] = np.repeat(sizes, sizes)
            rows = rows[rows["df"] > 1]
            yield _parcels(rows, rows["doc"] % width)

    return run


def _rarest(percent: int):
    """The rarest values of each set that leave no room for an unlisted partner: size - required overlap + 1 of them."""

    def run(batches):
        for rows in _gathered(batches):
            rows = rows[np.lexsort((rows["value"], rows["df"], rows["doc"]))]
            firsts = np.flatnonzero(np.concatenate([[True], rows["doc"][1:] != rows["doc"][:-1]]))
            s = np.diff(np.concatenate([firsts, [len(rows)]]))
            place = np.arange(len(rows)) - np.repeat(firsts, s)
            shared, n = np.repeat(s, s), rows["n"]
            take = place < shared - -(-n * percent // 100) + 1
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x[take])) for x in (rows["value"], rows["doc"], n, shared, shared / n)], ["value", "doc_id", "n", "s", "share"])

    return run


def full_lists(members: DataFrame, texts: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """Like inverted_lists, from the full sets of ``members`` (doc_id); exact: a pair as similar as asked shares a list.

    Also wide sketches (doc_id, sketch) of the members."""

    def run(batches):
        for batch in batches:
            data = [t or b"" for t in batch.column(1).to_pylist()]
            for a, z in chunks(data):
                sets = shingle_sets(data[a:z])
                ends = np.concatenate([[0], np.cumsum([len(x) for x in sets])]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, z - a), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(sets).astype(np.int64)))], ["doc_id", "all"])

    sets = texts.join(members, "doc_id", "left_semi").select("doc_id", F.col("text").cast("binary")).mapInArrow(trimmed(run), "doc_id bigint, all array<bigint>")
    sets = cut(sets, "full-sets")
    width = 4 * shuffle_width(texts.sparkSession)
    dealt = sets.mapInArrow(trimmed(_deal(width)), PARCEL)
    counted = dealt.repartition(width, "bucket").sortWithinPartitions("bucket").mapInArrow(trimmed(_count_shared(width)), PARCEL)
    listed = counted.repartition(width, "bucket").sortWithinPartitions("bucket").mapInArrow(trimmed(_rarest(percent)), "value bigint, doc_id bigint, n bigint, s bigint, share double")
    listed = cut(listed, "full-lists")
    # A text that shares at most s shingles reaches only partners of up to (100 + p) / p * s - n shingles.
    least = listed.groupBy("value").agg(F.min("n").alias("least"))
    near = listed.join(least, "value").filter(F.col("s") * (100 + percent) >= (F.col("n") + F.col("least")) * percent).drop("least")
    return near, sets.select("doc_id", F.slice("all", 1, WIDE).alias("sketch"))


def _estimated(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """Pairs whose sizes and union sketch leave the similarity asked for possible; further columns stay."""
    side = {x: reps.select(F.col("doc_id").alias(x), F.col("n_shingles").alias(f"n{x}"), F.col("sketch").alias(f"s{x}")) for x in "ab"}
    both = pairs.join(side["b"], "b").join(side["a"], "a")
    both = both.filter(F.least("na", "nb") * 100 >= F.greatest("na", "nb") * percent)
    common = F.array_intersect("sa", "sb")
    union = F.slice(F.array_sort(F.array_union("sa", "sb")), 1, SKETCH)
    whole = (F.col("na") <= SKETCH) & (F.col("nb") <= SKETCH)
    exact = F.size(common) * 100 >= (F.col("na") + F.col("nb") - F.size(common)) * percent
    likely = F.size(F.array_intersect(union, common)) >= LIKELY
    return both.filter(F.when(whole, exact).otherwise(likely)).select(*pairs.columns)


def _meet(percent: int):
    """Hubs (role 0) of a list meet its members (role 1; role 2: both) -> pairs (a, b) that may be similar enough.

    Two sketches know the union up to the smaller of their largest values; what they share of it is the estimate. The sketches
    of a short list are one matrix, multiplied once; in a long list one hub at a time marks its values among those of all
    members, so memory follows the sketches and not the pairs.

    A pair that meets in several lists is told in one: the least value that the smallest lists of both (``TOLD`` at most) have
    in common and in which one of the two is a hub. All lists decide alike, from these two short arrays; where they have no such
    value the pair shares few of its lists, and each of them tells it."""

    def told_once(met, h, value_of, listed, told, told_hub, code, values):
        """Of the members met by hub h those whose pair this list tells."""
        at = int(np.searchsorted(values, value_of))
        ends = np.cumsum(listed)
        own = np.zeros((2, len(values)), dtype=bool)
        mine = slice(ends[h] - listed[h], ends[h])
        own[0, code[mine]], own[1, code[mine]] = True, told_hub[mine]
        sizes = listed[met]
        firsts = np.cumsum(sizes) - sizes
        spots = np.repeat(ends[met] - sizes - firsts, sizes) + np.arange(sizes.sum())
        theirs = code[spots]
        common = own[0, theirs] & (own[1, theirs] | told_hub[spots])
        least = np.minimum.reduceat(np.where(common, theirs, len(values)), firsts)
        return (least == len(values)) | ((least == at) & (values[min(at, len(values) - 1)] == value_of))

    def candidates(value_of, role, doc, comp, n, s, sizes, flat, listed, told, told_hub):
        first_member = int(np.argmax(role > 0))  # those that are hubs only come first
        m, hubs = np.arange(first_member, len(doc)), np.flatnonzero(role != 1)
        twice = np.isin(doc[m], doc[hubs])  # a hub is a member too: of two hubs the one of the smaller id tests
        fits = (comp[m] != comp[hubs, None]) & (np.minimum(s[m], s[hubs, None]) * (100 + percent) >= (n[m] + n[hubs, None]) * percent)
        fits &= ~twice | (doc[m] > doc[hubs, None])
        if not fits.any():
            return np.empty((0, 2), dtype=np.int64)
        firsts = np.cumsum(sizes) - sizes
        values, code = np.unique(flat, return_inverse=True)
        whole = sizes == n
        limit = np.where(whole, np.iinfo(np.int64).max, flat[firsts + sizes - 1])
        dense, lists = len(doc) * len(values) <= DENSE, None
        if dense:
            held = np.zeros((len(doc), len(values)), dtype=np.float32)
            held[np.repeat(np.arange(len(doc)), sizes), code] = 1
            all_common = (held[hubs] @ held[first_member:].T).astype(np.int64)
            # How many values of each row lie below each other row's limit.
            key = np.repeat(np.arange(len(doc)), sizes) * (len(values) + 1) + code
            upto = np.searchsorted(values, limit, side="right")
            below = lambda rows, at: np.searchsorted(key, rows[:, None] * (len(values) + 1) + upto[at]) - firsts[rows][:, None]
            all_known = np.where(limit[m] <= limit[hubs, None], below(hubs, m) + sizes[m], sizes[hubs, None] + below(m, hubs).T) - all_common
        mine = np.zeros(len(values), dtype=bool)
        member_code, member_flat, start = code[firsts[first_member] :], flat[firsts[first_member] :], firsts[m] - firsts[first_member]
        out = []
        for i in np.flatnonzero(fits.any(axis=1)).tolist():
            h = int(hubs[i])
            if dense:
                common, known = all_common[i], all_known[i]
            else:
                own = code[firsts[h] : firsts[h] + sizes[h]]
                mine[own] = True
                common = np.add.reduceat(mine[member_code].astype(np.int64), start)
                mine[own] = False
                theirs = np.where(limit[m] <= limit[h], sizes[m], np.add.reduceat((member_flat <= limit[h]).astype(np.int64), start))
                known = np.searchsorted(flat[firsts[h] : firsts[h] + sizes[h]], np.minimum(limit[m], limit[h]), side="right") + theirs - common
            may = np.where(whole[m] & whole[h], 100 * common >= percent * known, common >= percent / 100 * known - 5.6 * np.sqrt(percent * (100 - percent) / 10_000 * known))
            met = m[fits[i] & may]
            if len(met):
                if lists is None:
                    lists, list_code = np.unique(told, return_inverse=True)
                found = doc[met[told_once(met, h, value_of, listed, told, told_hub, list_code, lists)]]
                out.append(np.stack([np.minimum(found, doc[h]), np.maximum(found, doc[h])], axis=1))
        return np.concatenate(out) if out else np.empty((0, 2), dtype=np.int64)

    def run(batches):
        key, parts, done = None, [], []

        def close():
            if parts:
                rows = [np.concatenate(c) for c in zip(*parts)] if len(parts) > 1 else parts[0]
                if rows[0][-1] and (rows[0][0] == 0 or rows[0][-1] == 2):
                    done.append(candidates(key[0], *rows))

        for batch in batches:
            value, salt, *cells = (batch.column(i).to_numpy() for i in range(7))
            sketch, told = batch.column(7), batch.column(8)
            sizes, listed = sketch.value_lengths().to_numpy().astype(np.int64), told.value_lengths().to_numpy().astype(np.int64)
            ends, told_ends = (np.concatenate([[0], np.cumsum(x)]) for x in (sizes, listed))
            flat, lists = sketch.flatten().to_numpy(), told.flatten()
            told_value, told_hub = lists.field(0).to_numpy(), lists.field(1).to_numpy(zero_copy_only=False)
            cells = [np.asarray(c, dtype=np.int64) for c in cells]
            edges = np.concatenate([[0], np.flatnonzero((value[1:] != value[:-1]) | (salt[1:] != salt[:-1])) + 1, [len(value)]]).tolist() if len(value) else [0]
            for a, z in zip(edges, edges[1:]):
                own = (int(value[a]), int(salt[a]))
                if own != key:
                    close()
                    key, parts = own, []
                e, f = slice(ends[a], ends[z]), slice(told_ends[a], told_ends[z])
                parts.append([*(c[a:z] for c in cells), sizes[a:z], flat[e], listed[a:z], told_value[f], told_hub[f]])
            if parts:  # what waits for the next batch does not hold this one
                parts[-1] = [x.copy() for x in parts[-1]]
            if done:
                yield pairs(done)
                done = []
        close()
        if done:
            yield pairs(done)

    def pairs(done):
        found = np.unique(np.concatenate(done), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(found[:, 0])), pa.array(np.ascontiguousarray(found[:, 1]))], ["a", "b"])

    return run


def list_pairs(chosen: DataFrame, sketch: DataFrame, percent: int) -> DataFrame:
    """Distinct candidate pairs of lists with is_hub and members; crowded lists are met in chunks."""
    # The smallest lists of a text, apart for its lists from sketches and from full sets, which bound its partners differently.
    numbered = chosen.withColumn("at", F.row_number().over(W.partitionBy("doc_id", "s").orderBy("value"))).filter(F.col("at") <= TOLD)
    least = numbered.groupBy("doc_id", "s").agg(F.collect_list(F.struct("value", "is_hub")).alias("lists"))
    rows = chosen.join(least, ["doc_id", "s"]).join(sketch, "doc_id")
    chunks_ = F.ceil(F.col("members") / CHUNK).cast("int")
    # A hub goes to every chunk, to its own as a member too: one row with its sketch, not one for each part that it plays.
    own = F.pmod(F.xxhash64("doc_id"), chunks_).cast("int")
    salts = F.when(F.col("is_hub"), F.sequence(F.lit(0), chunks_ - 1)).otherwise(F.array(own))
    role = F.when(~F.col("is_hub"), 1).when(F.col("salt") == own, 2).otherwise(0)
    dealt = rows.withColumn("salt", F.explode(salts)).select("value", "salt", role.cast("int").alias("role"), "doc_id", "component", "n", "s", "sketch", "lists")
    met = dealt.repartition("value", "salt").sortWithinPartitions("value", "salt", "role")
    return met.mapInArrow(trimmed(_meet(percent)), "a bigint, b bigint").distinct()


def _verified(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Pairs whose full sets are similar enough. Texts meet by (hub, salt): a hub's set is held, members stream past."""
    salted = pairs.withColumn("salt", F.pmod(F.xxhash64("b"), F.lit(SALTS)).cast("int"))
    members = salted.join(texts.withColumnRenamed("doc_id", "b"), "b").select("a", "salt", F.lit(1).alias("role"), "b", "text")
    hubs = salted.select("a", "salt").distinct().join(texts.withColumnRenamed("doc_id", "a"), "a").select("a", "salt", F.lit(0).alias("role"), F.col("a").alias("b"), "text")

    def run(batches):
        hub, held, proof = None, None, None
        for batch in batches:
            a, role, b = (batch.column(i).to_pylist() for i in (0, 2, 3))
            texts = [t or b"" for t in batch.column(4).to_pylist()]
            found = []
            for i, z in chunks(texts):
                for at, (own, second) in zip(range(i, z), confirmed_sets(texts[i:z])):
                    if role[at] == 0:
                        hub, held, proof = a[at], own, second
                        continue
                    if hub != a[at]:
                        raise RuntimeError("a member came without its hub")
                    spots = np.minimum(np.searchsorted(held, own), len(held) - 1)
                    inter = int(((held[spots] == own) & (proof[spots] == second)).sum())
                    if 100 * inter >= percent * (len(held) + len(own) - inter):
                        found.append((hub, b[at]))
            yield pa.RecordBatch.from_arrays([pa.array([f[j] for f in found], pa.int64()) for j in (0, 1)], ["a", "b"])

    rows = members.union(hubs).repartition("a", "salt").sortWithinPartitions("a", "salt", "role")
    return rows.select("a", "salt", "role", "b", F.col("text").cast("binary")).mapInArrow(trimmed(run), "a bigint, b bigint")


def _hubs(lists: DataFrame, room: int) -> DataFrame:
    """Adds is_hub to lists with component: about ``room`` members of each list, of its small components first."""
    sizes = lists.groupBy("value", "component").agg(F.count("*").alias("size"))
    sizes = sizes.withColumn("step", F.floor(F.log2("size")).cast("int"))
    by_step = sizes.groupBy("value", "step").agg(F.sum("size").alias("rows"))
    below = by_step.groupBy("value").agg(F.collect_list(F.struct("step", "rows")).alias("steps"))  # at most 64 each
    upto = F.aggregate(F.filter("steps", lambda x: x["step"] <= F.col("step")), F.lit(0).cast("long"), lambda acc, x: acc + x["rows"])
    odds = sizes.join(below, "value").select("value", "component", (F.lit(float(room)) / upto).alias("odds"))
    draw = F.pmod(F.xxhash64("doc_id", F.lit(room)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    return lists.join(odds, ["value", "component"]).withColumn("is_hub", draw < F.col("odds")).drop("odds")


def _mixed(lists: DataFrame, labels: DataFrame) -> DataFrame:
    """The lists that hold more than one component, with component and members (their number)."""
    named = lists.join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    mixed = named.groupBy("value").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("members")).filter("lo <> hi").select("value", "members")
    return named.join(mixed, "value")


def near_links(docs: DataFrame, reps: DataFrame, k: int = LISTED, percent: int = PERCENT, need: int = NEED, crowd: int = CROWD) -> DataFrame:
    """Components (node, component) of the representatives that have a link. docs: doc_id, text, one row for each at least."""
    lists = inverted_lists(reps, k, percent, need)
    first = lists.groupBy("value").agg(F.max_by("doc_id", F.struct("share", -F.col("doc_id"))).alias("a"), F.count("*").alias("listed")).filter("listed > 1").drop("listed")
    lists = cut(lists.join(first, "value"), "lists-with-hub")
    star = lists.filter("doc_id <> a").groupBy("a", F.col("doc_id").alias("b")).agg(F.count("*").alias("lists"))
    pairs = cut(_estimated(star, reps, percent).groupBy("b").agg(F.max_by("a", F.struct("lists", -F.col("a"))).alias("a")).select("a", "b"), "pairs")
    # Texts of every member of a list, moved once; all rounds read only these.
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    texts = cut(own.join(lists.select("doc_id").distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id"]), "listed-texts")
    sketch = reps.select("doc_id", "sketch")
    spent, labels = lists, None  # written tables that only the next round reads
    lists, rebuilt, room, links = lists.drop("a"), False, max(crowd, HUBS), None
    while True:
        found = cut(_verified(pairs, texts, percent), "links")
        discard(pairs)
        release(docs.sparkSession)
        links = found if links is None else links.union(found)
        if labels is not None:
            discard(labels)
        labels = cut(components(links), "components")
        open_lists = cut(_mixed(lists, labels), "open-lists")
        discard(spent)
        crowded = open_lists.filter(F.col("members") > crowd)
        if not rebuilt and not crowded.isEmpty():
            rebuilt = True
            near, wide = full_lists(crowded.select("doc_id").distinct(), texts, percent)
            small = open_lists.filter(F.col("members") <= crowd).drop("members", "component")
            before, open_lists = open_lists, cut(_mixed(small.unionByName(near), labels), "open-lists")
            discard(before)
            sketch = cut(sketch.join(wide.select("doc_id"), "doc_id", "left_anti").union(wide), "sketches-and-wide")
        chosen = cut(_hubs(open_lists, room), "hubs")
        discard(open_lists)
        if chosen.isEmpty():
            return labels
        pairs = cut(list_pairs(chosen, sketch, percent), "pairs")
        lists, spent, room = chosen.filter("not is_hub").drop("is_hub", "component", "members"), chosen, room * 4


def _judged(docs: DataFrame, k: int, percent: int, need: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n_shingles, component_id, kept, class_id, text_key, stays per row; stays: the one text of its component."""
    require_columns(docs, id_col, text_col)
    sets = cut(sketches(docs, id_col, text_col), "sketches")
    names = renamed(sets)
    sets = with_nodes(sets, names) if names is None else cut(with_nodes(sets, names), "sketches-of-nodes")
    lone = F.col("n_shingles") == 0
    digest = F.when(lone, F.unhex(F.sha2(F.col("node").cast("string"), 256))).otherwise(F.col("set_key"))
    entries = sets.filter("doc_id is not null").select(F.col("node").alias("id"), digest.alias("digest"), F.col("n_shingles").alias("length"), F.lit(0).alias("check"), "doc_id", "text_key")
    classes = cut(merge_tree(entries, "smallest").select("doc_id", F.col("id").alias("node"), F.col("length").alias("n_shingles"), F.col("keep_id").alias("class"), "text_key"), "classes")
    leaders = classes.filter("node = class").select("node").distinct()
    reps = sets.filter(F.col("n_shingles") > 0).join(leaders, "node", "left_semi").dropDuplicates(["node"]).select(F.col("node").alias("doc_id"), "n_shingles", "sketch")
    reps = cut(reps, "representatives")
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), text_key(F.col(text_col)))
    labels = near_links(with_nodes(own, names).select(F.col("node").alias("doc_id"), "text"), reps, k, percent, need)
    named = classes.join(labels.withColumnRenamed("node", "class").hint("merge"), "class", "left").withColumn("component", F.coalesce("component", "class"))
    if names is not None:  # nodes are not ids: look up the smallest id of each class and component
        by_class = named.groupBy("class").agg(F.min("doc_id").alias("class_id"))
        by_component = named.groupBy("component").agg(F.min(F.struct("doc_id", "node")).alias("least"))
        named = named.join(by_class, "class").join(by_component, "component").withColumns({"component_id": F.col("least.doc_id"), "stays": F.col("node") == F.col("least.node")})
    else:
        named = named.withColumns({"class_id": F.col("class"), "component_id": F.col("component"), "stays": F.col("node") == F.col("component")})
    out = named.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"), "class_id", "text_key", "stays")
    none = F.lit(None).cast("long")
    orphans = sets.filter("doc_id is null").select("doc_id", "n_shingles", none, F.lit(True), none, "text_key", F.lit(True))
    return out.union(orphans)


def near_duplicates(docs: DataFrame, k: int = LISTED, percent: int = PERCENT, need: int = NEED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept, class_id (smallest id of the equal sets) per row."""
    return _judged(docs, k, percent, need, id_col, text_col).drop("text_key", "stays")


def keep_one(docs: DataFrame, k: int = LISTED, percent: int = PERCENT, need: int = NEED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay: one text of each component, judged row by row and not by id."""
    gone = _judged(docs, k, percent, need, id_col, text_col).filter(~F.col("stays")).select(F.col("doc_id").alias("__id"), F.col("text_key").alias("__text")).distinct()
    packed = docs.select(F.struct("*").alias("row"), F.col(id_col).cast("long").alias("__id"), text_key(F.col(text_col)).alias("__text"))
    return packed.join(gone.hint("merge"), ["__id", "__text"], "left_anti").select("row.*")


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i : i + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, least(len(ws), 1)) + 1)) AS i FROM w)),
z AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
i AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT x, y FROM i JOIN z p ON p.doc_id = x JOIN z q ON q.doc_id = y WHERE 100 * c >= 75 * (p.n + q.n - c)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT doc_id, doc_id AS t FROM documents UNION SELECT r.doc_id, e.y FROM r JOIN e ON r.t = e.x),
m AS (SELECT doc_id, min(t) AS component_id FROM r GROUP BY doc_id),
k AS (SELECT s.doc_id, md5(string_agg(g, chr(10) ORDER BY g)) AS f FROM s GROUP BY s.doc_id),
c AS (SELECT f, min(doc_id) AS class_id FROM k GROUP BY f)
SELECT w.doc_id, CAST(coalesce(z.n, 0) AS BIGINT) AS n_shingles, m.component_id, w.doc_id = m.component_id AS kept, coalesce(c.class_id, w.doc_id) AS class_id
FROM w JOIN m USING (doc_id) LEFT JOIN z USING (doc_id) LEFT JOIN k USING (doc_id) LEFT JOIN c USING (f)
"""
