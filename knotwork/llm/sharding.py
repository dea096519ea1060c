"""Balanced sharding by label propagation.

Documents that belong together (members of one link group, or the ends of an edge)
are pulled into one shard: every round joins the members with their groups' shard
histogram, lets each member ask for the shard where most of its neighbours are (of
those with room, if no shard can hold the group), and grants the requests in a keyed-hash order up to the quotas that keep every
shard within its target. A last exact step settles the row counts: members that
exceed their shard's target and documents without links fill the open places.

Law ``rows``: the shards' document counts differ by one at most.

Only a table of at most ``shards`` squared flows reaches the driver in a round; a
hot group is a histogram of at most ``shards`` rows on the other side of the join.

Defined cases: null text has size 1 and checksum 0 and no links; empty texts are
linked with each other; null doc_ids are numbered like any other row; repeated rows
are members of one group; equal requests and votes are settled by keyed hash; fewer
rows than shards leave the last shards empty; a very long text is one row like any
other; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import documents, stored, with_global_index


def memberships(edges: DataFrame) -> DataFrame:
    """Edges (src, dst) as (doc_id, grp) link groups: each vertex with its
    neighbours is a group named by that vertex."""
    both = edges.select(F.col("src").alias("doc_id"), F.col("dst").alias("grp")).unionByName(
        edges.select(F.col("dst").alias("doc_id"), F.col("src").alias("grp"))
    )
    own = both.select("grp").distinct().select(F.col("grp").alias("doc_id"), "grp")
    return both.unionByName(own).where("doc_id is not null and grp is not null").distinct()


def propagate(links: DataFrame, shards: int, targets: list[int], rounds: int = 4, seed: int = 11) -> DataFrame:
    """(row, grp) link rows to (row, label): a shard for every linked row.

    ``targets`` are the most linked rows a shard may hold after a round (one that
    starts above its target only loses rows)."""
    label = F.pmod(F.xxhash64(F.lit(seed), F.col("row")), F.lit(shards)).cast("int")
    state = stored(links.select("row").distinct().withColumn("label", label), "labels")
    for turn in range(rounds):
        loads = {r["label"]: r["n"] for r in state.groupBy("label").agg(F.count("*").alias("n")).collect()}
        open_ = [s for s in range(shards) if loads.get(s, 0) < targets[s]]
        seated = links.join(state, "row")
        # Stored, so that the joins have a plain exchange on both sides and adaptive
        # execution can split a hot group's members.
        per = stored(seated.groupBy("grp", "label").agg(F.count("*").alias("weight")), "histogram")
        # At most `shards` rows a group: bounded windows, however large the group. A group
        # that no shard can hold asks for its fullest shard with room, any other for its
        # fullest, since opposite moves between full shards still cancel.
        whole = F.sum("weight").over(Window.partitionBy("grp"))
        order = Window.partitionBy("grp").orderBy(F.desc("weight"), F.xxhash64(F.lit(seed), "grp", "label"))
        sized = per.withColumn("split", whole > F.lit(max(targets))).where(~F.col("split") | F.col("label").isin(open_))
        best = sized.withColumn("k", F.row_number().over(order)).where("k = 1").select("grp", F.col("label").alias("want"), "weight", "split")
        best = stored(best, "wanted")
        votes = seated.join(best, "grp")
        # Members of such a group vote for where they are, too, and stay in its fuller shards.
        stay = votes.where("split and want <> label").select("row", "grp", "label").join(per, ["grp", "label"]).select("row", "label", F.col("label").alias("want"), "weight")
        asked = (
            votes.select("row", "label", "want", "weight").unionByName(stay).groupBy("row", "label", "want").agg(F.sum("weight").alias("w"))
            .groupBy("row", "label").agg(F.max_by("want", F.struct("w", F.col("want") != F.col("label"), "want")).alias("want"))
        )
        asked = stored(asked.withColumn("turn", F.pmod(F.xxhash64(F.lit(seed + turn), F.col("row")), F.lit(1 << 20))), "asked")
        flows = {(r["label"], r["want"]): r["n"] for r in asked.groupBy("label", "want").agg(F.count("*").alias("n")).collect()}
        grant = quotas(flows, targets)
        moving = [(i, j, int(share * (1 << 20))) for (i, j), share in grant.items()]
        if not any(share for _, _, share in moving):
            break
        allowed = F.create_map(*[x for i, j, cut in moving for x in (F.lit(i * shards + j), F.lit(cut))])
        go = F.col("turn") < F.coalesce(allowed[F.col("label") * shards + F.col("want")], F.lit(0))
        state = stored(asked.select("row", F.when(go, F.col("want")).otherwise(F.col("label")).alias("label")), "labels")
    return state


def quotas(flows: dict[tuple[int, int], int], targets: list[int]) -> dict[tuple[int, int], float]:
    """The share of each requested flow i->j that may go. Opposite flows always
    cancel; beyond those a shard takes in what its target leaves open."""
    loads = [sum(n for (i, _), n in flows.items() if i == s) for s in range(len(targets))]
    moves = {k: n for k, n in flows.items() if k[0] != k[1]}
    swap = {(i, j): min(n, moves.get((j, i), 0)) for (i, j), n in moves.items()}
    rest = {k: n - swap[k] for k, n in moves.items()}
    out = {}
    for (i, j), n in moves.items():
        into = sum(m for (_, b), m in rest.items() if b == j)
        room = max(0, targets[j] - loads[j])
        out[i, j] = min(1.0, (swap[i, j] + (rest[i, j] * min(1.0, room / into) if into else 0)) / n)
    return out


def shard_rows(docs: DataFrame, shards: int = 8, rounds: int = 4) -> DataFrame:
    """All documents into ``shards`` shards under law ``rows``, equal texts
    together as far as the counts allow. Returns doc_id, size, text_crc32, law,
    shard, slot, grown_shard, and label (the shard propagation chose; null for
    documents without links)."""
    raw = F.encode("text", "UTF-8")
    base = documents(docs).select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32(raw), F.lit(0)).cast("long").alias("text_crc32"),
        F.unhex(F.md5(raw)).alias("grp"),
    )
    rows, total = with_global_index(base, [F.col("doc_id"), F.col("grp"), F.col("size")], "row", "sized")
    rows = stored(rows, "rows")
    shared = stored(rows.where("grp is not null").groupBy("grp").agg(F.count("*").alias("n")).where("n > 1").select("grp"), "shared")
    links = stored(rows.select("row", "grp").join(shared, "grp").select("row", "grp"), "links")
    goal = [total // shards + (s < total % shards) for s in range(shards)]
    labels = propagate(links, shards, goal, rounds)
    return settle(rows.join(labels, "row", "left"), goal)


def settle(rows: DataFrame, goal: list[int]) -> DataFrame:
    """Exact counts and gapless slots from preferred labels (null: anywhere)."""
    shards = len(goal)
    first = F.coalesce(F.col("label"), F.lit(shards))
    ranked, total = with_global_index(rows.withColumn("first", first), [F.col("first"), F.col("grp"), F.col("row")], "place", "ranked")
    loads = {r["first"]: r["n"] for r in ranked.groupBy("first").agg(F.count("*").alias("n")).collect()}
    held = [loads.get(s, 0) for s in range(shards)]
    starts = [sum(held[:s]) for s in range(shards + 1)]
    stays = [min(h, g) for h, g in zip(held, goal, strict=True)]
    over = [h - k for h, k in zip(held, stays, strict=True)]
    spilt = [sum(over[:s]) for s in range(shards + 1)]  # surplus rows come before the unlinked as fillers
    room = [g - k for g, k in zip(goal, stays, strict=True)]
    upto = [sum(room[: s + 1]) for s in range(shards)]
    at = lambda values, i: F.element_at(F.array(*[F.lit(int(v)).cast("long") for v in values]), i + 1)
    inside = F.col("place") - at(starts, F.col("first"))
    seated = (F.col("first") < shards) & (inside < at([*stays, 0], F.col("first")))
    filler = at(spilt, F.col("first")) + inside - at([*stays, 0], F.col("first"))
    taken = sum(((F.lit(u) <= F.col("filler")).cast("int") for u in upto), F.lit(0))
    # A filler fills the shards' open places in order; taken counts the shards already full.
    out = ranked.withColumn("seated", seated).withColumn("filler", F.when(~seated, filler))
    shard = F.when(F.col("seated"), F.col("first")).otherwise(taken).cast("int")
    out = out.withColumn("shard", shard)
    slot = F.when(F.col("seated"), inside).otherwise(at(stays, F.col("shard")) + F.col("filler") - at([0, *upto], F.col("shard")))
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", slot.cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"), "label",
    )


def shard_edges(vertices: DataFrame, edges: DataFrame, shards: int = 8, rounds: int = 6) -> DataFrame:
    """The same for vertices (doc_id, distinct) and links (src, dst): doc_id,
    shard, slot."""
    ids = vertices.select(F.col("doc_id").cast("long").alias("row")).withColumns({"doc_id": F.col("row"), "size": F.lit(1).cast("long"), "text_crc32": F.lit(0).cast("long"), "grp": F.lit(None).cast("binary")})
    total = ids.count()
    goal = [total // shards + (s < total % shards) for s in range(shards)]
    labels = propagate(stored(memberships(edges).select(F.col("doc_id").alias("row"), "grp"), "links"), shards, goal, rounds)
    return settle(ids.join(labels, "row", "left"), goal).select("doc_id", "shard", "slot")


def cut(assigned: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: edges, and those whose ends are in different shards."""
    a = assigned.select(F.col("doc_id").alias("src"), F.col("shard").alias("s"))
    b = assigned.select(F.col("doc_id").alias("dst"), F.col("shard").alias("d"))
    return edges.join(a, "src").join(b, "dst").agg(F.count("*").alias("n_edges"), F.sum((F.col("s") != F.col("d")).cast("long")).alias("n_cut"))


def cut_groups(assigned: DataFrame, goal: int) -> DataFrame:
    """One row from (grp, shard) rows: groups of two or more, those in several shards,
    and those that must be because they exceed ``goal``, a shard's count."""
    per = assigned.groupBy("grp", "shard").agg(F.count("*").alias("n")).groupBy("grp").agg(F.sum("n").alias("n"), F.count("*").alias("shards")).where("n > 1")
    return per.agg(F.count("*").alias("groups"), F.count_if(F.col("shards") > 1).alias("cut"), F.count_if(F.col("n") > goal).alias("least"))
