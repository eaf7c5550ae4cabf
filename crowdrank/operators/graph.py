"""Interaction graphs, groups, ties, degrees, statistics and centralities."""

from __future__ import annotations

import itertools
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.session import shared_dir

Cols = list[str | Column]
#: Whether Spark deletes the shuffle files of a query at its end.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Users of one context that meet in one task; larger contexts are dealt to blocks of about so many.
CONTEXT_BLOCK = 1024
#: Users of a block whose ties to another block are found in one task, as a table of bits.
TIE_BLOCK = 8192
#: Rows of cells that one task mines for groups, and pairs of a row and a context it looks at together.
CELL_ROWS, CELL_EDGES = 524_288, 2_000_000


def store(df: DataFrame) -> DataFrame:
    """Cut the lineage of an iteration by a table in the shared folder of ``spark.checkpoint.dir``.

    Nothing reads the shuffle files behind the table again, so they go as soon as it is written.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/step-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEANUP, before) if before else spark.conf.unset(CLEANUP)
    return spark.read.schema(df.schema).parquet(path)


# --- interaction graphs and groups


def build_uv(log: DataFrame, weight: str = "count") -> DataFrame:
    """User-item edges with their first time; ``weight``: ``count`` of records or ``binary``."""
    w = F.count("*").cast("double") if weight == "count" else F.lit(1.0)
    return log.filter("user_id IS NOT NULL AND item_id IS NOT NULL").groupBy("user_id", "item_id").agg(w.alias("w"), F.min("ts").alias("ts"))


def group_key(members: Column) -> Column:
    return F.array_join(members.cast("array<string>"), "-")


def explicit_groups(log: DataFrame, key: str, least: int = 2, more: Cols = ()) -> DataFrame:
    """Records of groups that the log names: one row a key and item, with ``more`` aggregates."""
    g = log.groupBy(key, "item_id").agg(F.array_sort(F.collect_set("user_id")).alias("members"), F.max("ts").alias("ts"), *more).filter(F.size("members") >= least)
    return g.select(group_key(F.col("members")).alias("group_key"), "members", "item_id", "ts", *g.columns[4:])


def mine_groups(log: DataFrame, uu: DataFrame, cell: Cols, least: int = 2, mode: str = "component", context: Cols | None = None) -> DataFrame:
    """Tied users in the same cell (place and time) form a group.

    ``component``: connected within the cell; ``pairwise``: every tied pair; ``clique``: maximal sets
    of mutually tied users, found inside one cell at a time. ``context``: what tied users share, if a
    tie is one shared context; components and cliques are then found from it without listing a tie.
    """
    names = ["item_id", "bucket"]
    present = log.select("user_id", *cell, "ts").groupBy("user_id", *names).agg(F.max("ts").alias("ts"))
    if context is not None and mode != "pairwise":
        return _mined_by_context(present, shared_contexts(log, context), least, mode)
    pairs = _tied_in_cells(present, uu, names)
    if mode == "pairwise":
        sets = pairs.filter("a < b").select(*names, F.array("a", "b").alias("members"))
    elif mode == "clique":
        sets = pairs.groupBy(*names).applyInPandas(_cliques, f"{_ddl(pairs, names)}, members array<long>")
    else:
        sets = _components_in(pairs, names)
    one = sets.select(*names, "members", F.explode("members").alias("user_id")).join(present, [*names, "user_id"])
    last = one.groupBy(*names, "members").agg(F.max("ts").alias("ts")).filter(F.size("members") >= least)
    return last.select(group_key(F.col("members")).alias("group_key"), "members", "item_id", "ts")


def _tied_in_cells(present: DataFrame, uu: DataFrame, names: list[str], most: int = 8) -> DataFrame:
    """``names, a, b``: tied users of the same cell, both directions.

    Where cells are small (pairs of a cell at most ``most`` times the rows) pairs are made within cells
    and kept if tied; otherwise users meet their friends first and those in the same cell are kept.
    """
    a = present.select(*names, F.col("user_id").alias("a"))
    b = present.select(*names, F.col("user_id").alias("b"))
    ties = uu.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    sizes = present.groupBy(*names).count().agg(F.sum("count").alias("n"), F.sum(F.col("count") * (F.col("count") - 1)).alias("pairs")).first()
    if (sizes["pairs"] or 0) <= most * (sizes["n"] or 0):
        return a.join(b.toDF(*b.columns), names).filter("a <> b").join(ties, ["a", "b"], "left_semi").select(*names, "a", "b")
    return a.join(ties, "a").join(b, [*names, "b"], "left_semi").select(*names, "a", "b")


def dealt(rows: DataFrame, users: DataFrame, lists: DataFrame):
    """Rows with a share ``_b`` beside the lists of the users (``_b, user_id``) of that share.

    A user's list goes once to each share that asks for it, not once to each row.
    """
    wanted = users.distinct().join(lists, "user_id")
    return rows.groupBy("_b").cogroup(wanted.toDF(*wanted.columns).groupBy("_b"))


def _mined_by_context(present: DataFrame, lists: DataFrame, least: int, mode: str) -> DataFrame:
    present = store(present.filter("user_id IS NOT NULL AND item_id IS NOT NULL AND bucket IS NOT NULL"))
    n = max(1, -(-present.count() // CELL_ROWS))
    rows = present.withColumn("_b", F.pmod(F.xxhash64("item_id", "bucket"), F.lit(n)).cast("int"))
    ddl = f"members array<long>, {_ddl(present, ['item_id', 'ts'])}"
    # nearly every share asks for nearly every list, so lists travel as bytes of their gaps
    found = dealt(rows, rows.select("_b", "user_id"), packed_lists(lists)).applyInArrow(lambda a, b: _mined(a, b, least, mode), ddl)
    return store(found.select(group_key(F.col("members")).alias("group_key"), "members", "item_id", "ts"))


def _mined(a: pa.Table, b: pa.Table, least: int, mode: str) -> pa.Table:
    """Groups of all cells of a share; users are linked through the contexts that they share."""
    members, where, at = [], [], []
    if a.num_rows and b.num_rows:
        known = b["user_id"].to_numpy()
        by_id = np.argsort(known, kind="stable")
        cuts, flat = unpacked_lists(b["at"])
        start, size = cuts[:-1][by_id], np.diff(cuts)[by_id]
        values, codes = np.unique(flat, return_inverse=True)
        user = a["user_id"].to_numpy()
        spot = np.searchsorted(known[by_id], user).clip(0, len(known) - 1)
        bucket = a["bucket"].combine_chunks().dictionary_encode()
        cell = np.unique(a["item_id"].to_numpy(), return_inverse=True)[1] * len(bucket.dictionary) + bucket.indices.to_numpy()
        order = np.lexsort((user, cell))
        order = order[known[by_id][spot[order]] == user[order]]
        cell, spot = cell[order], spot[order]
        time = a["ts"].cast(pa.timestamp("us", getattr(a["ts"].type, "tz", None))).cast(pa.int64()).fill_null(-(1 << 63)).to_numpy()[order]
        ends = np.append(np.flatnonzero(np.diff(cell)) + 1, len(cell))
        done = np.cumsum(size[spot])
        i = 0
        while i < len(order):
            upto = np.searchsorted(done, (done[i - 1] if i else 0) + CELL_EDGES, side="right")
            k = np.searchsorted(ends, upto, side="right")
            j = int(ends[k - 1]) if k and ends[k - 1] > i else int(ends[np.searchsorted(ends, i, side="right")])
            n = size[spot[i:j]]
            row = np.repeat(np.arange(j - i), n)
            ctx = codes[np.arange(len(row)) + np.repeat(start[spot[i:j]] - (np.cumsum(n) - n), n)]
            meet = cell[i:j][row].astype(np.int64) * len(values) + ctx
            for g in _linked(row, meet) if mode == "component" else _mutual(row, meet, ctx, cell[i:j]):
                if len(g) >= least:
                    rows = order[i + g]
                    members.append(user[rows])
                    last = i + g[np.argmax(time[i + g])]
                    where.append(order[last])
            i = j
        at = np.array(where, np.int64)
    out = pa.ListArray.from_arrays(np.cumsum([0, *map(len, members)]).astype(np.int32), pa.array(np.concatenate(members) if members else [], pa.int64()))
    at = pa.array(at, pa.int64())
    return pa.table({"members": out, "item_id": a["item_id"].take(at), "ts": a["ts"].take(at)})


def flat_lists(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """List cells as one array, and where each begins and ends in it."""
    c = column.combine_chunks()
    c = c if isinstance(c, pa.ListArray) else pa.concat_arrays(c.chunks)
    cuts = c.offsets.to_numpy().astype(np.int64)
    return cuts - cuts[0], c.flatten().to_numpy(zero_copy_only=False)


def packed_lists(lists: DataFrame) -> DataFrame:
    """``user_id, at``: ascending numbers as bytes of their gaps, seven bits a byte, the last one below 128."""

    def run(batches):
        for b in batches:
            cuts, flat = flat_lists(pa.chunked_array([b.column("at")]))
            gap = np.diff(flat, prepend=0)
            first = cuts[:-1][np.diff(cuts) > 0]
            gap[first] = flat[first]
            size = 1 + sum((gap >= 1 << k).astype(np.int64) for k in range(7, 63, 7))
            end = np.append(0, np.cumsum(size))
            data = np.zeros(end[-1], np.uint8)
            for k in range(size.max(initial=0)):
                has = size > k
                data[end[:-1][has] + k] = (gap[has] >> 7 * k & 127) | (size[has] > k + 1) << 7
            at = pa.Array.from_buffers(pa.binary(), len(b), [None, pa.py_buffer(end[cuts].astype(np.int32)), pa.py_buffer(data)])
            yield pa.RecordBatch.from_arrays([b.column("user_id"), at], ["user_id", "at"])

    return lists.select("user_id", "at").mapInArrow(run, f"{_ddl(lists, ['user_id'])}, at binary")


def unpacked_lists(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """What ``flat_lists`` gave before ``packed_lists``."""
    sizes, parts = [np.zeros(1, np.int64)], [np.zeros(0, np.int64)]
    for c in column.chunks:
        if not len(c):
            continue
        cuts = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1].astype(np.int64)
        data = np.frombuffer(c.buffers()[2] or b"", np.uint8)[cuts[0] : cuts[-1]]
        stop = np.flatnonzero(data < 128)
        start = np.append(0, stop + 1)[: len(stop)]
        size, gap = stop - start + 1, np.zeros(len(stop), np.int64)
        for k in range(size.max(initial=0)):
            has = size > k
            gap[has] |= (data[start[has] + k] & 127).astype(np.int64) << 7 * k
        cuts = np.searchsorted(start, cuts - cuts[0])
        total = np.append(0, np.cumsum(gap))
        sizes.append(np.diff(cuts))
        parts.append(total[1:] - np.repeat(total[cuts[:-1]], np.diff(cuts)))
    return np.cumsum(np.concatenate(sizes)), np.concatenate(parts)


def _met(row: np.ndarray, meet: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs of a row and a meeting where others are too: rows and meetings in order of meetings, and the cuts."""
    by = np.argsort(meet, kind="stable")
    cut = np.flatnonzero(np.diff(meet[by], prepend=-1))
    many = np.repeat(np.diff(cut, append=len(by)), np.diff(cut, append=len(by))) > 1
    by = by[many]
    return row[by], by, np.flatnonzero(np.diff(meet[by], prepend=-1))


def _linked(row: np.ndarray, meet: np.ndarray) -> list[np.ndarray]:
    """Connected rows: smallest labels go through meetings, with shortcuts, until nothing changes."""
    own, by, cut = _met(row, meet)
    if not len(own):
        return []
    n = np.diff(cut, append=len(own))
    back = np.argsort(by, kind="stable")  # pairs in order of rows, which is how they came
    rows = own[back]
    first = np.flatnonzero(np.diff(rows, prepend=-1))
    label = np.arange(int(row.max()) + 1)
    while True:
        low = np.repeat(np.minimum.reduceat(label[own], cut), n)[back]
        new = label.copy()
        new[rows[first]] = np.minimum(label[rows[first]], np.minimum.reduceat(low, first))
        new = new[new]
        if (new == label).all():
            break
        label = new
    at = rows[first]
    at = at[np.argsort(label[at], kind="stable")]
    return np.split(at, np.flatnonzero(np.diff(label[at])) + 1)


def _mutual(row: np.ndarray, meet: np.ndarray, ctx: np.ndarray, cell: np.ndarray) -> list[np.ndarray]:
    """Maximal sets of rows that all meet each other, cell by cell.

    Rows that meet the same rows and each other stand in the same sets, so one of them stands for all.
    """
    own, by, _ = _met(row, meet)
    back = np.argsort(by, kind="stable")
    own, ctx, out = own[back], ctx[by[back]], []
    for part in np.split(np.arange(len(own)), np.flatnonzero(np.diff(cell[own])) + 1) if len(own) else []:
        ids, r = np.unique(own[part], return_inverse=True)
        kinds, c = np.unique(ctx[part], return_inverse=True)
        x = np.zeros((len(ids), len(kinds)), np.float32)
        x[r, c] = 1
        tied = x @ x.T > 0
        twins: dict[bytes, list[int]] = {}
        for k, bits in enumerate(np.packbits(tied, axis=1)):
            twins.setdefault(bits.tobytes(), []).append(k)
        sets = list(twins.values())
        one = [s[0] for s in sets]
        small = tied[np.ix_(one, one)]
        near = {k: set(np.flatnonzero(small[k]).tolist()) - {k} for k in range(len(one))}
        out += [ids[sorted(i for k in m for i in sets[k])] for m in _maximal(near)]
    return out


def _ddl(df: DataFrame, names: list[str]) -> str:
    return ", ".join(f"{n} {df.schema[n].dataType.simpleString()}" for n in names)


def _components_in(pairs: DataFrame, names: list[str]) -> DataFrame:
    """Label minima along ties in all cells at once, with shortcuts, until nothing changes.

    A user takes the smallest label of its neighbours and then the label of that label, so chains
    shorten by doubling and rounds grow with the logarithm of the diameter.
    """
    pairs = store(pairs)
    label = store(pairs.groupBy(*names, "a").agg(F.least(F.min("b"), F.first("a")).alias("l")))
    while True:
        near = pairs.join(label.withColumnRenamed("a", "b"), [*names, "b"]).groupBy(*names, "a").agg(F.min("l").alias("m"))
        new = label.join(near, [*names, "a"]).select(*names, "a", F.least("l", "m").alias("to"), F.col("l").alias("was"))
        far = label.select(*names, F.col("a").alias("to"), F.col("l").alias("far"))
        new = store(new.join(far, [*names, "to"]).select(*names, "a", F.least("to", "far").alias("l"), "was"))
        if not new.filter("l <> was").limit(1).count():
            return new.groupBy(*names, "l").agg(F.array_sort(F.collect_set("a")).alias("members")).drop("l")
        label = new.drop("was")


def _cliques(pdf):
    import pandas as pd

    near: dict[int, set[int]] = {}
    for a, b in zip(pdf["a"], pdf["b"], strict=True):
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    head = pdf.iloc[:1].drop(columns=["a", "b"])
    return pd.concat([head.assign(members=[m]) for m in _maximal(near)], ignore_index=True)


def _maximal(near: dict[int, set[int]]) -> list[list[int]]:
    """Maximal sets of mutual neighbours."""
    out, todo = [], [(set(), set(near), set())]
    while todo:  # branch on users outside the best pivot's neighbours
        chosen, may, done = todo.pop()
        if not may and not done:
            out.append(sorted(chosen))
            continue
        pivot = max(may | done, key=lambda u: len(near[u] & may))
        for u in list(may - near[pivot]):
            todo.append((chosen | {u}, may & near[u], done & near[u]))
            may.discard(u)
            done.add(u)
    return out


def canonical_groups(records: DataFrame) -> DataFrame:
    """Equal member sets are one group: ``group_id, group_key, members, n``."""
    return records.groupBy("group_key").agg(F.first("members").alias("members")).select(F.xxhash64("members").alias("group_id"), "group_key", "members", F.size("members").alias("n"))


def membership(records: DataFrame) -> DataFrame:
    return canonical_groups(records).select("group_key", F.explode("members").alias("user_id"))


def group_items(records: DataFrame) -> DataFrame:
    """Group-item edges of weight 1 with their first time."""
    return records.groupBy("group_key", "item_id").agg(F.lit(1.0).alias("w"), F.min("ts").alias("ts"))


# --- social network


def symmetrise(pairs: DataFrame) -> DataFrame:
    one = pairs.select("src", "dst").filter("src <> dst")
    return one.union(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def derive_ties(log: DataFrame, context: Cols, tau: int = 1) -> DataFrame:
    """Users who share at least ``tau`` contexts; both directions.

    The ties are all pairs of a context, so they are the size of the result; a context of many users
    is dealt to blocks, and a task holds two blocks of it.
    """
    rows = log.select("user_id", *context).distinct()
    keys = [c for c in rows.columns if c != "user_id"]
    blocks = rows.groupBy(*keys).agg(F.ceil(F.count("*") / CONTEXT_BLOCK).cast("int").alias("_nb"))
    dealt = rows.join(blocks, keys).withColumn("_own", F.pmod(F.xxhash64("user_id"), F.col("_nb")).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.col("_nb") - 1))
    left = dealt.select(*keys, F.col("user_id").alias("src"), F.col("_own").alias("_i"), every.alias("_j"))
    right = dealt.select(*keys, F.col("user_id").alias("dst"), F.col("_own").alias("_j"), every.alias("_i"))
    both = left.join(right.toDF(*right.columns), [*keys, "_i", "_j"]).filter("src <> dst")
    if tau <= 1:
        return both.select("src", "dst").distinct()
    return both.groupBy("src", "dst").count().filter(F.col("count") >= tau).select("src", "dst")


def shared_contexts(log: DataFrame, context: Cols) -> DataFrame:
    """``user_id, at``: numbers of the contexts that each user shares with somebody.

    Two users are tied by one context if their lists meet; lists are the size of the log.
    """
    rows = log.select("user_id", *context).filter("user_id IS NOT NULL").distinct()
    keys = [c for c in rows.columns if c != "user_id"]
    many = rows.groupBy(*keys).agg(F.count("*").alias("_n")).filter("_n > 1")
    many = store(many.select(*keys, F.monotonically_increasing_id().alias("_c")))
    # numbers without gaps, as their lists are written and sent by their differences
    part = many.groupBy(F.shiftright("_c", 33).alias("_p")).agg(F.count("*").alias("_n"))
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    part = part.select("_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    many = many.withColumn("_p", F.shiftright("_c", 33)).join(F.broadcast(part), "_p").select(*keys, (F.col("_c").bitwiseAND((1 << 33) - 1) + F.col("_base")).alias("_c"))
    return store(rows.join(many, keys).groupBy("user_id").agg(F.array_sort(F.collect_list("_c")).alias("at")))


def _tie_blocks(lists: DataFrame, found, schema: str) -> DataFrame:
    """Runs ``found(rows, columns, tied)`` on each two blocks of users, and on the same turned round.

    ``tied`` is a table of bits in id order of both sides. Blocks meet once; no tie is written.
    """
    n = max(1, -(-lists.count() // TIE_BLOCK))
    own = F.pmod(F.xxhash64("user_id"), F.lit(n)).cast("int")
    x = lists.withColumn("lb", own).withColumn("rb", F.explode(F.sequence(F.col("lb"), F.lit(n - 1))))
    y = lists.withColumn("rb", own).withColumn("lb", F.explode(F.sequence(F.lit(0), F.col("rb"))))

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return found(a.slice(0, 0), b.slice(0, 0), np.zeros((0, 0), bool))
        a, b = a.sort_by("user_id"), b.sort_by("user_id")
        tied = np.zeros((a.num_rows, b.num_rows), bool)
        sides = []
        for t in (a, b):
            cuts, flat = flat_lists(t["at"])
            user = np.repeat(np.arange(t.num_rows), np.diff(cuts))
            by = np.argsort(flat, kind="stable")
            sides.append((*np.unique(flat[by], return_index=True), user[by]))
        (ka, sa, ua), (kb, sb, ub) = sides
        _, ia, ib = np.intersect1d(ka, kb, assume_unique=True, return_indices=True)
        ea, eb = np.append(sa[1:], len(ua)), np.append(sb[1:], len(ub))
        for i, j in zip(ia.tolist(), ib.tolist(), strict=True):
            tied[ua[sa[i] : ea[i]][:, None], ub[sb[j] : eb[j]]] = True
        if a["lb"][0] == b["rb"][0]:
            np.fill_diagonal(tied, False)
            return found(a, b, tied)
        return pa.concat_tables([found(a, b, tied), found(b, a, np.ascontiguousarray(tied.T))])

    return x.groupBy("lb", "rb").cogroup(y.toDF(*y.columns).groupBy("lb", "rb")).applyInArrow(run, schema)


def context_degrees(lists: DataFrame) -> DataFrame:
    """``user_id, score``: the number of users tied by ``lists`` of shared contexts, as ``centrality_degree``."""

    def found(a: pa.Table, b: pa.Table, tied: np.ndarray) -> pa.Table:
        return pa.table({"user_id": a["user_id"], "n": pa.array(tied.sum(1), pa.int64())})

    return _tie_blocks(lists, found, "user_id long, n long").groupBy("user_id").agg(F.sum("n").cast("double").alias("score")).filter("score > 0")


def context_neighbours(lists: DataFrame, scores: DataFrame, k: int = 4) -> DataFrame:
    """``top_neighbours`` along the ties of ``lists``: the best of each block, then the best of these."""

    def found(a: pa.Table, b: pa.Table, tied: np.ndarray) -> pa.Table:
        score, ids = b["score"].to_numpy(), b["user_id"].to_numpy()
        order = np.lexsort((ids, -score))
        tied, rows, out = tied[:, order], np.arange(a.num_rows), []
        for _ in range(min(k, tied.shape[1])):
            at = tied.argmax(1)
            ok = tied[rows, at]
            tied[rows, at] = False
            out.append((rows[ok], order[at[ok]]))
        r, c = (np.concatenate([o[i] for o in out]) if out else np.zeros(0, np.int64) for i in (0, 1))
        return pa.table({"src": a["user_id"].take(pa.array(r)), "dst": pa.array(ids[c], pa.int64()), "score": pa.array(score[c], pa.float64())})

    best = _tie_blocks(lists.join(scores, "user_id"), found, "src long, dst long, score double")
    order = Window.partitionBy("src").orderBy(F.desc("score"), "dst")
    return best.withColumn("rnk", F.row_number().over(order)).filter(F.col("rnk") <= k).select(F.col("src").alias("user_id"), "rnk", F.col("dst").alias("nbr"), "score")


def degrees(edges: DataFrame, side: str) -> DataFrame:
    return edges.groupBy(F.col(side).alias("id")).agg(F.sum("w").alias("degree"))


def graph_stats(uv: DataFrame, gv: DataFrame, members: DataFrame, degree: DataFrame) -> DataFrame:
    """Users, groups, items, average group size, interactions by group and user, friends by user.

    ``degree``: ties of each user, as ``centrality_degree`` has them.
    """
    n = lambda df, c: df.agg(F.count_distinct(c).alias("n"))
    r = lambda df, a, b, name: df.agg(F.round(F.count("*") / F.count_distinct(a), 6).alias(name))
    parts = [
        n(uv, "user_id").withColumnRenamed("n", "users"),
        n(gv, "group_key").withColumnRenamed("n", "groups"),
        n(uv, "item_id").withColumnRenamed("n", "items"),
        r(members, "group_key", "user_id", "avg_group_size"),
        r(gv, "group_key", "item_id", "interactions_per_group"),
        r(uv, "user_id", "item_id", "items_per_user"),
        degree.agg(F.coalesce(F.sum("score"), F.lit(0.0)).alias("ties")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.crossJoin(p)  # one row each
    friends = F.round(F.col("ties") / F.col("users"), 6).alias("friends_per_user")
    return out.select("users", "groups", "items", "avg_group_size", "interactions_per_group", "items_per_user", friends)


def density(edges: DataFrame, left: str, right: str) -> DataFrame:
    return edges.agg(F.count("*").alias("edges"), F.round(F.count("*") / (F.count_distinct(left) * F.count_distinct(right)), 9).alias("density"), F.round(F.count("*") / F.count_distinct(left), 6).alias("per_left"))


def cold_flags(test: DataFrame, train: DataFrame) -> DataFrame:
    """Groups of the test part that no training record holds."""
    return test.select("group_key").distinct().join(train.select("group_key").distinct(), "group_key", "left_anti")


def cold_members(test: DataFrame, train: DataFrame) -> DataFrame:
    """``group_key, members, new_members``: how many members of a test group were in no training group."""
    known = train.select(F.explode("members").alias("user_id")).distinct().withColumn("known", F.lit(1))
    rows = test.select("group_key", F.explode("members").alias("user_id")).distinct().join(known, "user_id", "left")
    return rows.groupBy("group_key").agg(F.count("*").alias("members"), F.count_if(F.col("known").isNull()).alias("new_members"))


# --- centralities


def centrality_degree(uu: DataFrame) -> DataFrame:
    return uu.groupBy(F.col("src").alias("user_id")).agg(F.count("*").cast("double").alias("score"))


def centrality_pagerank(uu: DataFrame, damping: float = 0.85, iters: int = 20, every: int = 5, tol: float | None = None) -> DataFrame:
    """Rounds over a symmetric graph (so no node dangles); lineage cut every few.

    With ``tol`` it ends before ``iters`` where no score moved by more in the rounds since the last cut.
    """
    out = uu.groupBy("src").agg(F.count("*").alias("k"))
    links = store(uu.join(out, "src"))
    n = out.count()
    now, old = out.select(F.col("src").alias("user_id"), F.lit(1.0 / max(1, n)).alias("score")), None
    for i in range(iters):
        sent = links.join(now, links["src"] == now["user_id"]).groupBy("dst").agg(F.sum(F.col("score") / F.col("k")).alias("s"))
        now = sent.select(F.col("dst").alias("user_id"), (F.lit((1 - damping) / max(1, n)) + damping * F.col("s")).alias("score"))
        if i % every == every - 1:
            now = store(now)
            if tol is not None and old is not None:
                moved = now.join(old.withColumnRenamed("score", "was"), "user_id").agg(F.max(F.abs(F.col("score") - F.col("was")))).first()[0]
                if moved is None or moved <= tol:
                    break
            old = now
    return now


def centrality_eigenvector(uu: DataFrame, iters: int = 20, every: int = 5) -> DataFrame:
    """Power iteration, scaled by the largest score every few rounds and at the end.

    Scaling does not change the direction, so the rounds between need no maximum.
    """
    now = uu.select(F.col("src").alias("user_id")).distinct().withColumn("score", F.lit(1.0))
    for i in range(iters):
        now = uu.join(now, uu["src"] == now["user_id"]).groupBy(F.col("dst").alias("user_id")).agg(F.sum("score").alias("score"))
        if i % every == every - 1 or i == iters - 1:
            now = store(now)
            top = now.agg(F.max("score")).first()[0] or 1.0
            now = now.select("user_id", (F.col("score") / F.lit(top)).alias("score"))
    return now


def distances(uu: DataFrame, sources: DataFrame, limit: int | None = None) -> DataFrame:
    """Breadth-first levels from many sources at once: ``source, node, dist, sigma`` (path counts).

    Levels end where nothing new is reached; a ``limit`` that comes first is an error.
    """
    front = sources.select(F.col("user_id").alias("source"), F.col("user_id").alias("node"), F.lit(0).alias("dist"), F.lit(1.0).alias("sigma"))
    seen = front = store(front)
    for d in itertools.count(1):
        step = front.join(uu, front["node"] == uu["src"]).groupBy("source", F.col("dst").alias("node")).agg(F.sum("sigma").alias("sigma"))
        front = store(step.join(seen.select("source", "node"), ["source", "node"], "left_anti").select("source", "node", F.lit(d).alias("dist"), "sigma"))
        if not front.limit(1).count():
            return seen
        if limit is not None and d > limit:
            raise RuntimeError(f"distances have not ended after {limit} levels")
        seen = store(seen.unionByName(front))


def picked(nodes: DataFrame, k: int) -> DataFrame:
    """``k`` nodes in a reproducible pseudo-random order."""
    return nodes.orderBy(spread(F.col("user_id"), F.lit(0), 1), "user_id").limit(k)


def centrality_harmonic(uu: DataFrame) -> DataFrame:
    """Sum of the reciprocal distances to all nodes reached; what the sketched closeness estimates."""
    d = distances(uu, uu.select(F.col("src").alias("user_id")).distinct())
    return d.groupBy(F.col("source").alias("user_id")).agg(F.sum(F.when(F.col("dist") > 0, 1 / F.col("dist")).otherwise(0.0)).alias("score"))


def centrality_closeness(uu: DataFrame, landmarks: int | None = None) -> DataFrame:
    """Reached nodes over the sum of their distances, times the reached share of the graph.

    With ``landmarks`` distances are taken to that many nodes, picked by hash.
    """
    nodes = uu.select(F.col("src").alias("user_id")).distinct()
    n = nodes.count()
    sources = nodes if landmarks is None else picked(nodes, landmarks)
    d = distances(uu, sources).filter("dist > 0").groupBy(F.col("node").alias("user_id")).agg(F.sum("dist").alias("total"), F.count("*").alias("reached"))
    other = (n if landmarks is None else landmarks) - (1 if landmarks is None else 0)
    return nodes.join(d, "user_id", "left").select("user_id", F.coalesce(F.col("reached") / F.col("total") * F.col("reached") / F.lit(max(1, other)), F.lit(0.0)).alias("score"))


def centrality_closeness_sketch(uu: DataFrame, hops: int | None = None) -> DataFrame:
    """Sum over hops of newly reached nodes divided by the hop, reached sets kept as sketches.

    Ends where no sketch changes, or after ``hops``.
    """
    now = store(uu.select("src").distinct().groupBy("src").agg(F.hll_sketch_agg("src").alias("h")))
    size = now.select("src", F.lit(1.0).alias("n"), F.lit(0.0).alias("score"))
    for hop in itertools.count(1) if hops is None else range(1, hops + 1):
        before = now
        near = uu.join(now.withColumnRenamed("src", "dst"), "dst").select("src", "h").union(now)
        now = store(near.groupBy("src").agg(F.hll_union_agg("h").alias("h")))
        if hops is None and not now.join(before.select("src", F.col("h").alias("was")), "src").filter(F.hll_sketch_estimate("h") != F.hll_sketch_estimate("was")).limit(1).count():
            break
        grown = now.select("src", F.hll_sketch_estimate("h").cast("double").alias("m"))
        size = store(size.join(grown, "src").select("src", F.col("m").alias("n"), (F.col("score") + F.greatest(F.col("m") - F.col("n"), F.lit(0.0)) / hop).alias("score")))
    return size.select(F.col("src").alias("user_id"), "score")


def centrality_betweenness(uu: DataFrame, pivots: int | None = None) -> DataFrame:
    """Shortest-path dependencies added backwards over breadth-first levels, halved for pairs.

    ``pivots`` samples that many sources and scales the result up.
    """
    nodes = uu.select(F.col("src").alias("user_id")).distinct()
    n = nodes.count()
    sources = nodes if pivots is None else picked(nodes, pivots)
    level = store(distances(uu, sources))
    deepest = level.agg(F.max("dist")).first()[0] or 0
    delta = None
    for d in range(deepest, 0, -1):
        own = level.filter(F.col("dist") == d)
        own = own.withColumn("delta", F.lit(0.0)) if delta is None else own.join(delta, ["source", "node"], "left").withColumn("delta", F.coalesce("delta", F.lit(0.0)))
        up = level.filter(F.col("dist") == d - 1).select("source", F.col("node").alias("parent"), F.col("sigma").alias("ps"))
        flow = own.join(uu, own["node"] == uu["src"]).select("source", F.col("dst").alias("parent"), "sigma", "delta").join(up, ["source", "parent"])
        got = store(flow.groupBy("source", F.col("parent").alias("node")).agg(F.sum(F.col("ps") / F.col("sigma") * (1 + F.col("delta"))).alias("delta")))
        delta = got
        parts = got if d == deepest else parts.unionByName(got)
    if delta is None:
        return nodes.withColumn("score", F.lit(0.0))
    inner = parts.filter("node <> source").groupBy(F.col("node").alias("user_id")).agg(F.sum("delta").alias("s"))
    scale = 0.5 * (1 if pivots is None else n / pivots)
    return nodes.join(inner, "user_id", "left").select("user_id", (F.coalesce("s", F.lit(0.0)) * scale).alias("score"))


MEASURES = {"degree": centrality_degree, "pagerank": centrality_pagerank, "closeness": centrality_closeness, "betweenness": centrality_betweenness, "eigenvector": centrality_eigenvector}


# --- neighbours and walks


def top_neighbours(uu: DataFrame, scores: DataFrame, k: int = 4) -> DataFrame:
    """Each user's ``k`` neighbours of the highest score, ties to the smaller id."""
    near = uu.join(scores.select(F.col("user_id").alias("dst"), "score"), "dst")
    order = Window.partitionBy("src").orderBy(F.desc("score"), "dst")
    return near.withColumn("rnk", F.row_number().over(order)).filter(F.col("rnk") <= k).select(F.col("src").alias("user_id"), "rnk", F.col("dst").alias("nbr"), "score")


def spread(a: Column, b: Column, seed: int) -> Column:
    """A reproducible pseudo-random order of pairs, in plain integer arithmetic."""
    return F.pmod(a * 7919 + b * 104729 + F.lit(seed) * 1299709, F.lit(1000003))


def sample_neighbours(uu: DataFrame, k: int = 4, seed: int = 1) -> DataFrame:
    order = Window.partitionBy("src").orderBy(spread(F.col("src"), F.col("dst"), seed), "dst")
    return uu.withColumn("rnk", F.row_number().over(order)).filter(F.col("rnk") <= k).select(F.col("src").alias("user_id"), "rnk", F.col("dst").alias("nbr"))


def walk_corpus(uu: DataFrame, length: int = 8, per_node: int = 2, p: float = 1.0, q: float = 1.0, seed: int = 3) -> DataFrame:
    """Random walks as arrays. With ``p`` or ``q`` off 1 the step is biased by the last edge:
    1/p back, 1 to a common neighbour, 1/q further away."""
    near = store(uu.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("near")))
    walks = near.select("src", F.explode(F.sequence(F.lit(1), F.lit(per_node))).alias("walk")).select("src", "walk", F.array("src").alias("path"))
    for step in range(1, length):
        at = walks.withColumn("at", F.element_at("path", -1)).join(near.withColumnRenamed("src", "at"), "at")
        u = F.pmod(F.xxhash64("src", "walk", F.lit(step), F.lit(seed)), F.lit(1 << 40)) / float(1 << 40)
        if p == 1.0 and q == 1.0 or step == 1:
            nxt = F.element_at("near", (F.floor(u * F.size("near")) + 1).cast("int"))
            walks = at.select("src", "walk", F.concat("path", F.array(nxt)).alias("path"))
        else:
            at = at.withColumn("was", F.element_at("path", -2)).join(near.select(F.col("src").alias("was"), F.col("near").alias("wasnear")), "was")
            weight = F.transform("near", lambda x: F.when(x == F.col("was"), 1 / p).when(F.array_contains("wasnear", x), 1.0).otherwise(1 / q))
            # one pass over the neighbours: the last one whose share of the total begins below ``u``
            at = at.withColumn("ws", weight).withColumn("total", F.aggregate("ws", F.lit(0.0), lambda s, y: s + y))
            start = F.struct(F.lit(0.0).alias("run"), F.lit(0).alias("n"))
            step_over = lambda s, y: F.struct((s["run"] + y).alias("run"), (s["n"] + F.when(s["run"] + y <= u * F.col("total"), 1).otherwise(0)).alias("n"))
            pick = F.aggregate("ws", start, step_over, lambda s: s["n"]) + 1
            walks = at.select("src", "walk", F.concat("path", F.array(F.element_at("near", F.least(pick, F.size("near"))))).alias("path"))
        if step % 4 == 0:
            walks = store(walks)
    return walks


def walk_embedding(walks: DataFrame, d: int = 16, window: int = 3, seed: int = 3, walks_each: int = 100_000) -> DataFrame:
    """Node vectors of the walks by Spark's skip-gram, on about ``walks_each`` walks a partition."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    parts = max(1, walks.count() // walks_each)
    model = Word2Vec(vectorSize=d, windowSize=window, minCount=0, maxIter=1, numPartitions=parts, seed=seed, inputCol="words", outputCol="v").fit(walks.select(F.col("path").cast("array<string>").alias("words")))
    return model.getVectors().select(F.col("word").cast("long").alias("user_id"), vector_to_array("vector").alias("vec"))
