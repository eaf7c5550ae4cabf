"""Similarity self-join on word n-grams by a MinHash LSH forest.

Each document has a set of n-grams of its lower-cased words. Documents with equal sets are one class
and stand for their copies. A class has a label of ``depth`` MinHash values in each of ``trees``
prefix tries; the labels of a tree are sorted, which shows how long a prefix each shares with its
neighbours, and labels without a long enough match leave here.

Matching starts with whole labels: classes connected by equal labels are a core, and within a core
every pair is verified. Then the matched prefix is shortened value by value. A shorter prefix offers
only pairs of different cores that no longer prefix and no earlier tree has offered. The similarities
of the links found so far say how many links the prefix still misses, as a pair of similarity ``s``
shares a prefix of ``d`` values in some tree with chance ``1 - (1 - s**d)**trees``. Shortening ends
once the estimated recall reaches ``recall``, and at the latest where every single pair at the
threshold has that chance. All offered pairs are verified exactly on the n-gram sets; groups larger
than ``block_docs`` meet block by block, and only counts and spanning links leave a task.

Result: ``doc_id, class_id, n_links, n_grams, th, first``: ``class_id`` is the smallest id connected by
links, ``n_links`` counts the other documents at or above the threshold, exact copies included, ``th``
is a hash of the text, and ``first`` holds for one text of each class, that of the smallest id.

Defined results: null, empty or blank text has no n-grams, links nothing and is its own class; a
text of fewer than ``n`` words has one n-gram of them all; repeated rows count as copies, also under
the same id, and rows of one id with different texts are judged by their texts; null ids are joined
like others, and ``class_id`` is null only where no document of the class has an id; ties in
similarity cannot matter, as the threshold is inclusive; an empty table gives no rows; extra columns
are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import cut, gram_hashes, lean, mix, table, word_hashes
from crowdrank.llm.components import components, star

#: Similarities from the threshold to 1 are counted in so many steps.
STEPS = 40


def gram_set(text: str | None, n: int) -> np.ndarray:
    words = word_hashes(text.lower().encode())[2] if text else np.zeros(0, np.uint64)
    return np.unique(gram_hashes(words, min(n, len(words)))) if len(words) else words


def set_key(grams: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(grams.tobytes())


def signature(grams: np.ndarray, a: np.ndarray, b: np.ndarray) -> bytes:
    """MinHash values (16 bits each, high byte first) of a non-empty set."""
    low = np.full(len(a), np.uint64(2**64 - 1))
    for i in range(0, len(grams), 1024):
        np.minimum(low, (grams[i : i + 1024, None] * a + b).min(axis=0), out=low)
    return (mix(low) >> np.uint64(48)).astype(">u2").tobytes()


def meeting(similarity: float | np.ndarray, depth: int, trees: int):
    """Chance that a pair shares a prefix of ``depth`` values in some tree."""
    return 1 - (1 - similarity**depth) ** trees


def shortest_needed(trees: int, depth: int, threshold: float, recall: float) -> int:
    """The depth at which even a pair at the threshold meets with chance ``recall``."""
    while depth > 1 and meeting(threshold, depth, trees) < recall:
        depth -= 1
    return depth


def estimated_recall(found: np.ndarray, threshold: float, depth: int, trees: int) -> float:
    """Share of the links that prefixes of ``depth`` values offer, judged by the links found.

    ``found``: links by step of similarity. Nothing found says nothing: 0.
    """
    steps = threshold + (1 - threshold) * np.arange(len(found)) / len(found)
    total = found.sum()
    return float(total / (found / meeting(steps, depth, trees)).sum()) if total else 0.0


def shared_prefix(tree: np.ndarray, high: np.ndarray, low: np.ndarray) -> np.ndarray:
    """Number of leading values (16 bits) that each row shares with the next one."""
    out = np.zeros(max(0, len(tree) - 1), np.int32)
    live = tree[1:] == tree[:-1]
    for part in (high, low):
        x = part[1:].view(np.uint64) ^ part[:-1].view(np.uint64)
        for values in (1, 2, 3, 4):
            live = live & (x >> np.uint64(64 - 16 * values) == 0)
            out += live
    return out


def matched_labels(batches, least: int):
    """Rows of sorted labels that share at least ``least`` values with a neighbour.

    What stands beyond the borders of a partition is not known here, so border rows stay.
    """
    held = None
    names = ["tree", "high", "low", "rid", "deep"]

    def rows(cols, deep):
        keep = deep >= least
        kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32()]
        return pa.RecordBatch.from_arrays([pa.array(c[keep], k) for c, k in zip([*cols, deep], kinds, strict=True)], names)

    for b in batches:
        if not b.num_rows:
            continue
        cols = [b.column(b.schema.get_field_index(c)).to_numpy() for c in names[:4]]
        before = 8
        if held is not None:
            cols = [np.concatenate((h, c)) for h, c in zip(held[0], cols, strict=True)]
            before = held[1]
        near = shared_prefix(*cols[:3])
        left = np.concatenate(([before], near)).astype(np.int32)
        yield rows([c[:-1] for c in cols], np.maximum(left[:-1], near))
        held = ([c[-1:] for c in cols], left[-1])
    if held is not None:
        yield rows(held[0], np.array([8], np.int32))


def shared_counts(left: list[np.ndarray], right: list[np.ndarray] | None) -> np.ndarray:
    """Sizes of the intersections of all sets of ``left`` with all of ``right`` (or of ``left``)."""
    both = left if right is None else left + right
    flat = np.concatenate(both)
    doc = np.repeat(np.arange(len(both)), [len(s) for s in both])
    _, gram, times = np.unique(flat, return_inverse=True, return_counts=True)
    live = times[gram] > 1
    ids = np.cumsum(times > 1)[gram[live]] - 1
    order = np.argsort(ids, kind="stable")
    ids, doc = ids[order], doc[live][order]
    shared = np.zeros((len(left), len(left) if right is None else len(right)), np.float32)
    width, top = 2048, int(ids[-1]) + 1 if len(ids) else 0
    for c in range(0, top, width):
        lo, hi = np.searchsorted(ids, (c, c + width))
        m = np.zeros((len(both), min(width, top - c)), np.float32)
        m[doc[lo:hi], ids[lo:hi] - c] = 1
        shared += m[: len(left)] @ (m if right is None else m[len(left) :]).T
    return shared


def similarities(left: list[np.ndarray], right: list[np.ndarray] | None, wanted: np.ndarray) -> np.ndarray:
    """Jaccard similarities of the pairs marked in ``wanted``, 0 for all others."""
    other = left if right is None else right
    out = np.zeros(wanted.shape)
    i, j = np.nonzero(wanted)
    if not len(i):
        return out
    if len(i) <= 4 * (len(left) + len(other)):
        own = np.array([len(np.intersect1d(left[x], other[y], assume_unique=True)) for x, y in zip(i, j, strict=True)], np.float64)
    else:
        own = shared_counts(left, right)[i, j].astype(np.float64)
    sizes = lambda s: np.array([len(x) for x in s], np.float64)
    out[i, j] = own / (sizes(left)[i] + sizes(other)[j] - own)
    return out


def spread(linked: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Smallest id connected within a symmetric link matrix, for each row."""
    root = np.arange(len(ids))
    by = np.argsort(ids)
    seen = np.zeros(len(ids), bool)
    for start in by:
        if not seen[start]:
            todo, seen[start] = [start], True
            while todo:
                x = todo.pop()
                root[x] = start
                new = np.flatnonzero(linked[x] & ~seen)
                seen[new] = True
                todo.extend(new)
    return ids[root]


def prefixes(sig: list[bytes], trees: int, depth: int) -> np.ndarray:
    """A hash of the first ``depth`` values of each label: rows by trees."""
    values = np.frombuffer(b"".join(sig), ">u2").reshape(len(sig), trees, -1)[:, :, :depth].astype(np.uint64)
    h = np.zeros(values.shape[:2], np.uint64)
    for k in range(depth):
        h = mix(h * np.uint64(0x2545F4914F6CDD1D) + values[:, :, k] + np.uint64(1))
    return h


def new_pairs(core: np.ndarray, tree: int, now: np.ndarray, before: np.ndarray) -> np.ndarray:
    """Pairs of different cores that neither a longer prefix nor an earlier tree has offered."""
    out = core[:, None] != core[None, :]
    for codes, some in ((before, range(before.shape[1])), (now, range(tree))):
        for t in some:
            if not out.any():
                return out
            out &= codes[:, t][:, None] != codes[:, t][None, :]
    return out


def verify(block: pa.Table, threshold: float, trees: int, depth: int, longer: int) -> pa.Table:
    """Links among the rows of each node, or across two blocks (``side`` 0 and 1) of a large one.

    Nodes of tree -1 are cores: all their pairs count. The first row has, in ``found``, the links by
    step of similarity, each document weighing one.
    """
    block = block.combine_chunks()
    tree, high, low, i, j, side, rid, core, copies = (block[c].to_numpy() for c in ("tree", "high", "low", "i", "j", "side", "rid", "core", "copies"))
    whole = block["whole"].to_numpy(zero_copy_only=False)
    sig, data = block["sig"].to_pylist(), block["grams"].to_pylist()
    out, found = [[], [], []], np.zeros(STEPS)
    order = np.lexsort((side, low, high, tree))
    keys = np.stack([tree.astype(np.int64), high, low], 1)[order]
    for own in np.split(order, np.flatnonzero((keys[1:] != keys[:-1]).any(1)) + 1):
        first = own[0]
        across = not whole[first] and i[first] != j[first]
        at = int((side[own] == 0).sum())
        if len(own) < 2 or across and at in (0, len(own)):
            continue
        if tree[first] < 0:
            wanted = ~np.eye(len(own), dtype=bool)
        else:
            mine = [sig[x] for x in own]
            wanted = new_pairs(core[own], int(tree[first]), prefixes(mine, trees, depth), prefixes(mine, trees, longer))
        if across:
            wanted = wanted[:at, at:]
        if not wanted.any():
            continue
        sets = [np.frombuffer(data[x], np.uint64) for x in own]
        near = similarities(sets[:at], sets[at:], wanted) if across else similarities(sets, None, wanted)
        linked = wanted & (near >= threshold - 1e-9)
        if across:
            square, values = np.zeros((len(own), len(own)), bool), np.zeros((len(own), len(own)))
            square[:at, at:], square[at:, :at] = linked, linked.T
            values[:at, at:], values[at:, :at] = near, near.T
            linked, near = square, values
        n = copies[own].astype(np.float64)
        links = linked @ n
        a, b = np.nonzero(linked)
        if len(a):
            step = np.clip(((near[a, b] - threshold) / (1 - threshold + 1e-12) * STEPS).astype(np.int64), 0, STEPS - 1)
            found += np.bincount(step, n[b] / links[a], STEPS)
            keep = links > 0
            for col, part in zip(out, (rid[own], links, spread(linked, rid[own])), strict=True):
                col.append(part[keep])
    cols = [np.concatenate(c) if c else np.zeros(0) for c in out]
    rows = len(cols[0])
    marks = pa.array([found.tolist()] + [None] * (rows - 1) if rows else [], pa.list_(pa.float64()))
    return pa.table([pa.array(c.astype(np.int64), pa.int64()) for c in cols] + [marks], ["rid", "links", "root", "found"])


VERIFIED = "rid long, links long, root long, found array<double>"
NODE = ["tree", "high", "low"]


def check(members: DataFrame, sets: DataFrame, n_rows: int, block_docs: int, **how) -> DataFrame:
    """Verify the nodes ``tree, high, low`` of ``members`` (with ``rid`` and the node's size ``n``).

    Nodes up to a block stay whole and share tasks; larger ones meet block by block.
    """
    tasks = max(1, (n_rows // block_docs + 1) * 2)
    rows = members.withColumn("nb", F.ceil(F.col("n") / block_docs).cast("int")).join(sets, "rid")
    given = ["rid", "core", "copies", "sig", "grams", *NODE]
    at = F.xxhash64(*NODE)
    zero = F.lit(0)
    small = rows.filter("nb = 1").select(*given, F.lit(True).alias("whole"), zero.cast("long").alias("of"), F.pmod(at, F.lit(tasks)).cast("int").alias("i"), zero.alias("j"), zero.alias("side"))
    big = rows.filter("nb > 1").withColumn("own", F.pmod(F.xxhash64("rid"), F.col("nb")).cast("int")).withColumn("o", F.explode(F.sequence(zero, F.col("nb") - 1)))
    big = big.select(*given, F.lit(False).alias("whole"), at.alias("of"), F.least("own", "o").alias("i"), F.greatest("own", "o").alias("j"), (F.col("own") > F.col("o")).cast("int").alias("side"))
    return cut(small.union(big).groupBy("whole", "of", "i", "j").applyInArrow(lambda t: verify(t, **how), VERIFIED), thin=True)


def prefix_at(depth: int) -> list[Column]:
    """The first ``depth`` values of a label that two columns hold, four values each."""
    mask = lambda n: F.lit(0 if n <= 0 else -(1 << (64 - 16 * min(n, 4)))).cast("long")
    return [F.col("high").bitwiseAND(mask(depth)).alias("high"), F.col("low").bitwiseAND(mask(depth - 4)).alias("low")]


def links_found(checked: DataFrame) -> np.ndarray:
    """Links by step of similarity over all tasks."""
    some = checked.filter("found IS NOT NULL")
    row = some.agg(*[F.sum(F.element_at("found", k + 1)).alias(f"s{k}") for k in range(STEPS)]).first()
    return np.array([x or 0.0 for x in row])


def signed_texts(text: DataFrame, n: int, trees: int, depth: int, seed: int) -> DataFrame:
    """``doc_id, th, key, n_grams, sig`` of each row of ``doc_id, th, t``."""
    rng = np.random.default_rng(seed)
    a, b = rng.integers(1, 2**63, trees * depth, dtype=np.uint64) | np.uint64(1), rng.integers(0, 2**63, trees * depth, dtype=np.uint64)

    def run(batches):
        for batch in batches:
            key, size, sig = [], [], []
            for t in batch.column(2):
                g = gram_set(t.as_py(), n)
                key.append(set_key(g) if len(g) else None)
                size.append(len(g))
                sig.append(signature(g, a, b) if len(g) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(key, pa.binary()), pa.array(size, pa.int32()), pa.array(sig, pa.binary())], ["doc_id", "th", "key", "n_grams", "sig"])

    return text.mapInArrow(lean(run), "doc_id long, th long, key binary, n_grams int, sig binary")


def sorted_labels(reps: DataFrame, trees: int, least: int) -> DataFrame:
    """``tree, high, low, rid, deep``: the labels that match a neighbour in their tree's sorted order."""

    def labels(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 2048):
                own = batch.slice(i, 2048)
                values = np.frombuffer(b"".join(own.column(1).to_pylist()), ">u8").reshape(own.num_rows, trees, 2).astype(np.uint64).view(np.int64)
                rid = np.repeat(own.column(0).to_numpy(), trees)
                tree = np.tile(np.arange(trees, dtype=np.int32), own.num_rows)
                yield pa.RecordBatch.from_arrays([pa.array(tree), pa.array(values[:, :, 0].ravel()), pa.array(values[:, :, 1].ravel()), pa.array(rid)], [*NODE, "rid"])

    by = [*NODE, "rid"]
    flat = reps.select("rid", "sig").mapInArrow(labels, "tree int, high long, low long, rid long")
    return flat.repartitionByRange(*by).sortWithinPartitions(*by).mapInArrow(lambda b: matched_labels(b, least), "tree int, high long, low long, rid long, deep int")


def gram_sets(reps: DataFrame, text: DataFrame, n: int) -> DataFrame:
    """``rid, core, copies, sig, grams`` for classes ``rid, key, copies, sig, at, core``."""

    def run(batches):
        for batch in batches:
            sets = [gram_set(t.as_py(), n) for t in batch.column(5)]
            real = pa.array([len(g) > 0 and set_key(g) == k for g, k in zip(sets, batch.column(4).to_pylist(), strict=True)], pa.bool_())
            cols = [*(batch.column(i) for i in range(4)), pa.array([g.tobytes() for g in sets], pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, ["rid", "core", "copies", "sig", "grams"]).filter(real)

    own = text.withColumnRenamed("doc_id", "text_id").withColumnRenamed("th", "text_hash")
    met = reps.join(own, (F.col("at.th") == F.col("text_hash")) & F.col("at.doc_id").eqNullSafe(F.col("text_id")))
    found = met.select("rid", "core", "copies", "sig", "key", "t").mapInArrow(lean(run), "rid long, core long, copies long, sig binary, grams binary")
    # rows repeated under one id bring their text more than once
    return found.dropDuplicates(["rid"])


def jaccard_classes(docs: DataFrame, n: int = 5, threshold: float = 0.8, trees: int = 24, depth: int = 8, recall: float = 0.99999, seed: int = 5, block_docs: int = 800, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    if depth != 8:
        raise ValueError("labels have eight values")
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(text_col)).alias("th"), F.col(text_col).alias("t"))
    signed = cut(signed_texts(text, n, trees, depth, seed))
    one = signed.filter("key IS NOT NULL").groupBy("key").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "th")).alias("at"), F.count("*").alias("copies"), F.min("sig").alias("sig"))
    reps = cut(one.withColumn("rid", F.monotonically_increasing_id()))
    least = shortest_needed(trees, depth, threshold, recall)
    tries = cut(sorted_labels(reps, trees, least))

    whole = tries.filter(F.col("deep") >= depth).select(*NODE, "rid")
    leads = whole.groupBy(*NODE).agg(F.min("rid").alias("lead"), F.count("*").alias("c")).filter("c > 1").drop("c")
    cores = components(star(whole.join(leads, NODE), "rid", "lead"))
    cores = cores.select(F.col("id").alias("rid"), F.col("root").alias("core"))
    wanted = tries.select("rid").distinct().join(cores, "rid", "left").select("rid", F.coalesce("core", "rid").alias("core"))
    sets = cut(gram_sets(reps.select("rid", "key", "copies", "sig", "at").join(wanted, "rid"), text, n))

    how = {"threshold": threshold, "trees": trees}
    sizes = cut(cores.groupBy("core").agg(F.count("*").alias("n")), thin=True)
    members = cores.join(sizes, "core").select("rid", F.lit(-1).alias("tree"), F.col("core").alias("high"), F.lit(0).cast("long").alias("low"), "n")
    done = [check(members, sets, cores.count(), block_docs, depth=depth, longer=depth, **how)]
    found, longer = links_found(done[0]), depth
    core_of = sets.select("rid", "core")
    for short in range(depth - 2, least - 1, -1):
        if estimated_recall(found, threshold, longer, trees) >= recall:
            break
        rows = tries.filter(F.col("deep") >= short).select("rid", "tree", *prefix_at(short))
        mixed = rows.join(core_of, "rid").groupBy(*NODE).agg(F.min("core").alias("a"), F.max("core").alias("b"), F.count("*").alias("n"))
        mixed = cut(mixed.filter("a <> b").select(*NODE, "n"), thin=True)
        n_rows = mixed.agg(F.sum("n")).first()[0]
        if n_rows:
            done.append(check(rows.join(mixed, NODE), sets, n_rows, block_docs, depth=short, longer=longer, **how))
            found = found + links_found(done[-1])
        longer = short

    checked = done[0]
    for more in done[1:]:
        checked = checked.union(more)
    links = checked.groupBy("rid").agg(F.sum("links").alias("links"))
    roots = components(star(checked.filter("rid <> root"), "rid", "root")).withColumnRenamed("id", "rid")
    own = cut(reps.select("key", "rid", "at", "copies").join(links, "rid", "left").join(roots, "rid", "left").select("key", "at", F.coalesce("root", "rid").alias("root"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links")))
    heads = own.groupBy("root").agg(F.min("at").alias("head"))
    classes = own.join(heads, "root").select("key", "head", "n_links")
    out = signed.select("doc_id", "th", "key", "n_grams").join(classes, "key", "left")
    alone = F.col("n_links").isNull()
    class_id = F.when(alone, F.col("doc_id")).otherwise(F.col("head.doc_id"))
    first = alone | (F.col("doc_id").eqNullSafe(F.col("head.doc_id")) & (F.col("th") == F.col("head.th")))
    return out.select("doc_id", class_id.alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.col("n_grams").cast("long").alias("n_grams"), "th", first.alias("first"))


def op3_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "class_id", "n_links", "n_grams")


SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(w[s:s + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 4) + 1)) AS s FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM g x JOIN g y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 5 * c >= 4 * (na.n + nb.n - c)),
r AS (SELECT doc_id AS id, doc_id AS root FROM documents UNION SELECT l.b, r.root FROM r JOIN l ON l.a = r.id),
c AS (SELECT id, min(root) AS class_id FROM r GROUP BY id),
k AS (SELECT a AS id, count(*) AS n_links FROM l GROUP BY a)
SELECT doc_id, class_id, coalesce(n_links, 0)::BIGINT AS n_links, coalesce(n.n, 0)::BIGINT AS n_grams
FROM documents JOIN c ON c.id = doc_id LEFT JOIN k ON k.id = doc_id LEFT JOIN n USING (doc_id)
"""
