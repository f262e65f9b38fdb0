"""MinHash near-dedup: chosen-path set similarity join over word shingles.

Each of eight trees starts from a minwise token of the shingle set under a hash of its own. A node holds the
documents that chose the same token path. A node with more than a few hundred documents that are not near its
head branches: it draws places of the minwise signature afresh from its own name, and a document goes to the
child of its token at each of them. Smaller nodes are compared exhaustively on signatures. A pair at 0.75 shares a root node with
0.75 and at least one child of a node with 1 - 0.25**3, so with three levels all eight trees miss it with
probability 5e-5; of pairs in one node, 3e-6 fall short on the signature. What the nodes propose only groups
documents into clusters; inside a cluster all links are found on full shingle sets.

Groups that stay large, nodes at the last level and clusters, are not taken into one task. All their rows
are compared with the row of the smallest id. Those near it are one component, so only the others need more
comparisons, among themselves and with all, in pairs of blocks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ._store import Workspace
from ._text import mix, raw, slices, windows, words

TREES = 8
SIGNATURE = 64
_rng = np.random.default_rng(7)
_TREE_KEYS = _rng.integers(1, 2**63, TREES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SIGN_KEYS = _rng.integers(1, 2**63, SIGNATURE, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: Equal signature places of 64 that make a pair worth a comparison of full sets. A pair at similarity
#: 0.75 has fewer than this with probability 3e-6.
LEAST_EQUAL = 32
#: Heads of large groups that are broadcast at most, by number and by the bytes they carry.
SMALL_HEADS, SMALL_HEAD_BYTES = 100_000, 32 << 20


def shingle_sets(column: pa.Array, width: int = 5) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text; one hash of all words where they are fewer."""
    buf, offsets = raw(column)
    _, _, hashes, at = words(buf, offsets)
    for i in range(len(offsets) - 1):
        own = hashes[at[i] : at[i + 1]]
        n = len(own)
        yield np.unique(windows(own, width)) if n >= width else windows(own, n) if n else own


def _signatures(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    keys = np.zeros((len(sets), TREES), np.uint64)
    signs = np.zeros((len(sets), SIGNATURE), np.uint64)
    for i, s in enumerate(sets):
        if len(s):
            most_k, most_s = np.full(TREES, 2**64 - 1, np.uint64), np.full(SIGNATURE, 2**64 - 1, np.uint64)
            for at in range(0, len(s), 4096):
                part = s[at : at + 4096, None]
                np.minimum(most_k, mix(part ^ _TREE_KEYS).min(0), out=most_k)
                np.minimum(most_s, (part * _SIGN_KEYS).min(0), out=most_s)
            keys[i], signs[i] = most_k, most_s
    return keys, mix(signs).astype(np.uint16)


def describe(docs: DataFrame, width: int) -> DataFrame:
    """doc_id, n_shingles, two halves of the set's 128-bit hash, tree keys and signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text"):
                sets = list(shingle_sets(batch.column("text"), width))
                keys, signs = _signatures(sets)
                sums = np.array([(int(mix(s).sum()), int(mix(s * np.uint64(3)).sum())) for s in sets], np.uint64)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id"),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array(sums[:, 0].view(np.int64)),
                        pa.array(sums[:, 1].view(np.int64)),
                        pa.FixedSizeListArray.from_arrays(pa.array(keys.view(np.int64).ravel()), TREES).cast(pa.list_(pa.int64())),
                        pa.array([x.tobytes() for x in signs], pa.binary()),
                    ],
                    names=["doc_id", "n_shingles", "h1", "h2", "keys", "sign"],
                )

    schema = "doc_id long, n_shingles long, h1 long, h2 long, keys array<long>, sign binary"
    return docs.mapInArrow(run, schema)


def near_links(sets: DataFrame, ws: Workspace, most: int, depth: int, picks: int = 3) -> DataFrame:
    """Links (a, b) that span the near documents of every node of the trees.

    The rows of a node of more than `most` are compared with its head. Where at most `most` rows, or at the
    last level any number, are not near it, they meet all others in blocks; other large nodes branch.
    """
    rows = sets.select("uid", "sign", F.posexplode("keys").alias("tree", "key")).select(F.xxhash64("tree", "key").alias("node"), "uid", "sign")
    signs = sets.select(F.col("uid").alias("head"), F.col("sign").alias("head_sign"))
    links, small = [], []
    for level in range(depth + 1):
        large = rows.groupBy("node").agg(F.count(F.lit(1)).alias("n"), F.min("uid").alias("head")).filter(F.col("n") > most)
        large = ws.save(large.select("node", "head"), f"large{level}")
        n_large = large.count()
        if not n_large:
            small.append(rows)
            break
        side = F.broadcast(large) if n_large <= SMALL_HEADS else large
        small.append(rows.join(side, "node", "left_anti").select("node", "uid", "sign"))
        heads = ws.save(signs.join(side, "head"), f"heads{level}")
        told = told_by_head(rows, heads, "node", "sign", near_head_signs, ws, f"told{level}")
        links.append(_head_links(told))
        sizes = ws.save(_near_and_far(told, "node"), f"sizes{level}")
        open_ = sizes.filter((F.col("far") > most) & F.lit(level < depth)).select("node")
        n_open = open_.count()
        small.append(_apart_from_head(told, sizes.filter((F.col("far") <= most) | F.lit(level == depth)), "node", most))
        if not n_open:
            break
        side = F.broadcast(open_) if n_open <= SMALL_HEADS else open_
        place = [F.pmod(F.xxhash64("node", F.lit(j)), F.lit(SIGNATURE)).cast("int") for j in range(picks)]
        chosen = F.array(*[F.struct(p.alias("place"), F.substring("sign", 2 * p + 1, 2).alias("token")) for p in place])
        rows = told.join(side, "node", "left_semi").withColumn("pick", F.explode(F.array_distinct(chosen)))
        rows = ws.save(rows.select(F.xxhash64("node", "pick.place", "pick.token").alias("node"), "uid", "sign"), f"level{level}")
    return _union([*links, propose(_union([x.select("node", "uid", "sign") for x in small]))])


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for x in frames[1:]:
        out = out.unionByName(x)
    return out


def _spread(ids: np.ndarray, signs: np.ndarray, out: list) -> None:
    """Spanning links of a node's documents under equality of LEAST_EQUAL signature places.

    Breadth first: each reached document is compared with all that are not reached yet.
    """
    left = np.arange(len(ids))
    while len(left) > 1:
        front, left, head = [left[0]], left[1:], ids[left[0]]
        while front and len(left):
            near = (signs[left] == signs[front.pop()]).sum(1) >= LEAST_EQUAL
            if near.any():
                got = left[near]
                front.extend(got)
                out.append((np.full(len(got), head), ids[got]))
                left = left[~near]


def _grouped(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Whole groups of a key from batches sorted by it; a group's parts wait until it ends."""
    wait: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(key).to_numpy(zero_copy_only=False)
        cuts = np.flatnonzero(keys[1:] != keys[:-1]) + 1
        if wait and wait[-1].column(key)[-1].as_py() != keys[0]:
            yield pa.Table.from_batches(wait)
            wait = []
        if len(cuts):
            if wait:
                yield pa.Table.from_batches([*wait, batch.slice(0, cuts[0])])
                wait = []
                yield from ([pa.Table.from_batches([batch.slice(cuts[0], cuts[-1] - cuts[0])])] if len(cuts) > 1 else [])
            else:
                yield pa.Table.from_batches([batch.slice(0, cuts[-1])])
            batch = batch.slice(cuts[-1])
        wait.append(batch)
    if wait:
        yield pa.Table.from_batches(wait)


def _runs(values: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.flatnonzero(values[1:] != values[:-1]) + 1, [len(values)]])


def propose(nodes: DataFrame) -> DataFrame:
    """Links (a, b), a spanning forest of each node's near documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _grouped(batches, "node"):
            node, uid = table.column("node").to_numpy(), table.column("uid").to_numpy()
            sign = np.frombuffer(b"".join(table.column("sign").to_pylist()), np.uint16).reshape(-1, SIGNATURE)
            out: list = []
            at = _runs(node)
            for i in np.flatnonzero(np.diff(at) > 1):
                _spread(uid[at[i] : at[i + 1]], sign[at[i] : at[i + 1]], out)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out)], names=["a", "b"])

    in_reach = nodes.repartition("node").withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("node"))).filter("n > 1")
    ordered = in_reach.select("node", "uid", "sign").sortWithinPartitions("node", "uid")
    return ordered.mapInArrow(run, "a long, b long")


def near_head_signs(rows: DataFrame) -> DataFrame:
    """(node, uid, head, sign, near): whether the signature has LEAST_EQUAL places in common with the head's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint16).reshape(-1, SIGNATURE) for c in ("sign", "head_sign"))
            cols = [batch.column(c) for c in ("node", "uid", "head", "sign")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array((one == two).sum(1) >= LEAST_EQUAL)], names=["node", "uid", "head", "sign", "near"])

    return rows.mapInArrow(run, "node long, uid long, head long, sign binary, near boolean")


def near_head_texts(rows: DataFrame, percent: int, width: int) -> DataFrame:
    """(cluster, uid, head, text, near): whether the full set is linked with the head's."""
    names = ["cluster", "uid", "head", "text", "near"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: tuple = (None, None)
        for whole in batches:
            for batch in slices(whole, "text"):
                head, near = batch.column("head").to_numpy(), np.zeros(batch.num_rows, bool)
                for i, own in enumerate(shingle_sets(batch.column("text"), width)):
                    if known[0] != head[i]:
                        known = head[i], next(shingle_sets(batch.column("head_text").slice(i, 1), width))
                    if not len(own) or not len(known[1]):
                        continue
                    place = np.minimum(np.searchsorted(known[1], own), len(known[1]) - 1)
                    both = int((known[1][place] == own).sum())
                    near[i] = 100 * both >= percent * (len(own) + len(known[1]) - both)
                yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names[:4]], pa.array(near)], names=names)

    return rows.select("cluster", "uid", "head", "text", "head_text").mapInArrow(run, "cluster long, uid long, head long, text string, near boolean")


def _smallest(rows: DataFrame, group: str, carried: str) -> DataFrame:
    """(group, head, head_ and the column `carried`) of each group's smallest uid."""
    first = rows.groupBy(group).agg(F.min("uid").alias("head"))
    heads = rows.join(F.broadcast(first) if first.count() <= SMALL_HEADS else first, group).filter("uid = head")
    return heads.select(group, "head", F.col(carried).alias(f"head_{carried}"))


def told_by_head(rows: DataFrame, heads: DataFrame, group: str, carried: str, near, ws: Workspace, name: str) -> DataFrame:
    """rows (group, uid and the column `carried`) of the groups of heads, each with its head and whether near(...) it."""
    weight = heads.agg(F.coalesce(F.sum(F.octet_length(f"head_{carried}")), F.lit(0))).first()[0]
    return ws.save(near(rows.join(F.broadcast(heads) if weight <= SMALL_HEAD_BYTES else heads, group)), name)


def _head_links(told: DataFrame) -> DataFrame:
    return told.filter("near and uid != head").select(F.col("head").alias("a"), F.col("uid").alias("b"))


def _near_and_far(told: DataFrame, group: str) -> DataFrame:
    return told.groupBy(group).agg(F.count_if("near").alias("close"), F.count_if(~F.col("near")).alias("far"))


def _apart_from_head(told: DataFrame, sizes: DataFrame, group: str, most: int) -> DataFrame:
    """Groups of bounded size in which rows that are not near their head meet each other and all that are.

    sizes has the counts of both kinds for the groups that count. Both kinds are dealt to blocks of about
    `most` rows, and every pair of blocks of which one is far gets a group of its own: no pair of rows is made
    here. Rows near the head are one component, so they need not be compared with each other.
    """
    blocks = sizes.filter("far > 0").select(group, *[F.ceil(F.col(c) / most).cast("int").alias(c) for c in ("close", "far")])
    rows = told.join(F.broadcast(blocks) if blocks.count() <= SMALL_HEADS else blocks, group)
    rows = rows.withColumn("own", F.pmod(F.xxhash64("uid"), F.when(F.col("near"), F.col("close")).otherwise(F.col("far"))).cast("int"))
    own, close, far = F.col("own"), F.col("close"), F.col("far")

    def others(n, name):
        """name(i) of the blocks 0 to n - 1, none where there is no block."""
        return F.when(n > 0, F.transform(F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0))), name)).otherwise(F.array().cast("array<bigint>"))

    def mixed(i, j):
        return F.xxhash64(group, F.lit("between"), i, j)

    among = others(far, lambda i: F.when((i != own) | (far == 1), F.xxhash64(group, F.least(i, own), F.greatest(i, own))))
    far_groups = F.concat(others(close, lambda j: mixed(own, j)), F.array_compact(among))
    groups = F.when(F.col("near"), others(far, lambda i: mixed(i, own))).otherwise(far_groups)
    return rows.withColumn(group, F.explode(groups)).drop("close", "far", "own", "near", "head")


def components(links: DataFrame, ws: Workspace, name: str) -> DataFrame:
    """(id, component): the smallest id that each id of a link can reach.

    Labels are spread over links and halved by jumping to the label's own label until none changes.
    """
    both = ws.save(links.union(links.select("b", "a")).distinct().toDF("id", "to"), f"{name}-links")
    labels = ws.save(both.groupBy("id").agg(F.least("id", F.min("to")).alias("component")), f"{name}-0")
    step = 0
    while True:
        step += 1
        by = labels.withColumnRenamed("id", "to").withColumnRenamed("component", "c")
        near = both.join(by, "to").groupBy("id").agg(F.min("c").alias("c"))
        lower = labels.join(near, "id").select("id", F.least("component", "c").alias("component"), F.col("component").alias("was"))
        head = labels.select(F.col("id").alias("component"), F.col("component").alias("head"))
        new = ws.save(
            lower.join(head, "component", "left").select("id", F.least("component", "head").alias("component"), "was"), f"{name}-{step}"
        )
        labels = new.select("id", "component")
        if new.filter("component != was").isEmpty():
            return labels


def _confirm(ids: np.ndarray, sets: list[np.ndarray], percent: int, out: list) -> None:
    """Spanning links of a cluster on full sets, breadth first against all sets not reached yet."""
    sizes = np.array([len(s) for s in sets])
    flat = np.concatenate(sets)
    _, token = np.unique(flat, return_inverse=True)
    n_tokens = int(token.max()) + 1 if len(token) else 0
    owner = np.repeat(np.arange(len(sets)), sizes)
    at = np.concatenate([[0], np.cumsum(sizes)])
    free = np.ones(len(sets), bool)
    mark = np.zeros(n_tokens, bool)
    live_token, live_owner = token, owner
    for first in range(len(sets)):
        if not free[first]:
            continue
        free[first] = False
        front = [first]
        while front and free.any():
            x = front.pop()
            mark[token[at[x] : at[x + 1]]] = True
            both = np.bincount(live_owner[mark[live_token]], minlength=len(sets))
            mark[token[at[x] : at[x + 1]]] = False
            near = free & (100 * both >= percent * (sizes + sizes[x] - both)) & (both > 0)
            if near.any():
                got = np.flatnonzero(near)
                free[got] = False
                front.extend(got)
                out.append((np.full(len(got), ids[first]), ids[got]))
            live = free[live_owner]
            if live.sum() * 2 < len(live):
                live_token, live_owner = live_token[live], live_owner[live]


def confirm(members: DataFrame, percent: int, width: int) -> DataFrame:
    """Links (a, b) that span the true components inside each cluster. members: cluster, uid, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _grouped(batches, "cluster"):
            cluster, uid = table.column("cluster").to_numpy(), table.column("uid").to_numpy()
            sets = [s for b in table.column("text").chunks for s in shingle_sets(b, width)]
            out: list = []
            at = _runs(cluster)
            for i in range(len(at) - 1):
                if at[i + 1] - at[i] > 1:
                    _confirm(uid[at[i] : at[i + 1]], sets[at[i] : at[i + 1]], percent, out)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out)], names=["a", "b"])

    ordered = members.repartition("cluster").sortWithinPartitions("cluster", "uid")
    return ordered.mapInArrow(run, "a long, b long")


def _with_class(rows: DataFrame, same: DataFrame, large: int = 256, small: int = 200_000) -> DataFrame:
    """rows with the uid of their class; classes of more than `large` rows are broadcast when these are few."""
    hot = same.filter(F.col("n") > large).drop("n")
    rest = same.filter(F.col("n") <= large).drop("n")
    if hot.count() > small:
        return rows.join(same.drop("n"), ["h1", "h2"])
    hot = F.broadcast(hot)
    apart = rows.join(hot, ["h1", "h2"], "left_anti").join(rest, ["h1", "h2"])
    return rows.join(hot, ["h1", "h2"]).unionByName(apart)


def near_components(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    percent: int = 75,
    width: int = 5,
    node_size: int = 256,
    depth: int = 3,
    cluster_size: int = 512,
    small_members: int = 1_000_000,
) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of each document.

    Links join documents with 100 * intersection >= percent * union of their distinct `width`-word
    shingles (A-Z folded). A text of fewer words is one shingle; null or wordless texts have none and
    stay alone. Rows are keyed by `id_col`: a null id gives a row of its own with a null component and
    kept true, rows that repeat an id are linked like other documents and share its component. Equal
    sets collapse to their smallest id before any comparison. Other columns are not read; an empty table
    gives no rows. A node of more than `node_size` sets branches, `depth` times at most; nodes that stay
    larger and clusters above `cluster_size` are compared by head and in blocks, not cut. A text is
    handled in one task, with work arrays of about 30 bytes for each of its bytes. Up to `small_members` cluster members are broadcast to fetch their texts, more are joined by shuffle.
    """
    ws = Workspace(docs.sparkSession, "near-dedup")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    described = ws.save(describe(texts, width), "described")
    known = described.filter("n_shingles > 0 and doc_id is not null")
    same = ws.save(known.groupBy("h1", "h2").agg(F.min("doc_id").alias("uid"), F.count(F.lit(1)).alias("n")), "same")
    classes = ws.save(_with_class(known.select("doc_id", "h1", "h2", "keys", "sign"), same), "classes")
    alone = classes.filter("doc_id = uid").select("uid", "keys", "sign")
    links = near_links(alone, ws, node_size, depth)
    clusters = components(links, ws, "near").select(F.col("id").alias("uid"), F.col("component").alias("cluster"))
    clusters = ws.save(clusters, "clusters")
    big = clusters.groupBy("cluster").count().filter(F.col("count") > cluster_size).select("cluster")
    some_big = big.count()
    true_links = confirm(_members(texts, clusters.join(big, "cluster", "left_anti") if some_big else clusters, small_members), percent, width)
    if some_big:
        whole = ws.save(_members(texts, clusters.join(big, "cluster", "left_semi"), small_members), "large-clusters")
        heads = ws.save(_smallest(whole, "cluster", "text"), "cluster-heads")
        told = told_by_head(whole, heads, "cluster", "text", lambda rows: near_head_texts(rows, percent, width), ws, "clusters-by-head")
        rest = _apart_from_head(told, ws.save(_near_and_far(told, "cluster"), "cluster-sizes"), "cluster", cluster_size // 2)
        true_links = true_links.unionByName(_head_links(told)).unionByName(confirm(rest, percent, width))
    true_links = ws.save(true_links, "linked")
    copies = classes.filter("doc_id != uid").select(F.col("uid").alias("a"), F.col("doc_id").alias("b"))
    found = components(true_links, ws, "true")
    reps = classes.select("doc_id", "uid").distinct()
    repeated = reps.groupBy("doc_id").count().filter("count > 1")
    if not repeated.isEmpty():  # an id on several texts ties their classes together
        found = components(true_links.unionByName(copies), ws, "tied")
        member = known.select("doc_id").distinct().join(found, F.col("doc_id") == F.col("id"), "left")
        member = member.select("doc_id", F.coalesce("component", "doc_id").alias("component_id"))
    else:
        member = reps.join(found, F.col("uid") == F.col("id"), "left").select("doc_id", F.coalesce("component", "uid").alias("component_id"))
    return (
        described.select("doc_id", "n_shingles")
        .join(member, "doc_id", "left")
        .select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )


def _members(texts: DataFrame, clusters: DataFrame, small: int) -> DataFrame:
    """(cluster, uid, text) of the representatives in clusters."""
    side = F.broadcast(clusters) if clusters.count() <= small else clusters
    return texts.join(side, F.col("doc_id") == F.col("uid")).select("cluster", "uid", "text")
