"""MinHash near-duplicates: a multi-index Hamming join on b-bit signatures, confirmed on full shingle sets.

A document's signature has ``PARTS`` components of 16 bits. It is cut into ``CHUNKS`` chunks; two signatures that differ in
at most ``2 * CHUNKS - 1`` components differ in at most one component of some chunk, so enumerating the one allowed error
(each chunk with one component left out) guarantees that every such pair shares a key. At a similarity of 0.8 a pair
differs in 12.8 components on average; 27 is 4.6 standard deviations above.

1. Texts with equal shingle sets collapse to their smallest doc_id, so groups of copies cost one row each.
2. Keys travel as packed blobs; buckets keep the keys that several documents share, and equal member lists collapse. Keys with
   very many members are counted first, by mergeable counters of fixed size, and dealt in blocks without a bucket.
3. Members of a key are clustered by signature distance without listing pairs: each member is compared with those
   not yet reached. Only tree edges leave; star contraction joins them across keys.
4. The full shingle sets of each cluster meet once, links are confirmed exactly (integer arithmetic) by the same
   search, and star contraction gives the components. Keys and clusters with more members than a block are compared block
   pair by block pair, so that no task holds more than two blocks, whatever the group's size.

Edge cases: null and empty texts have no shingle and link with nothing; a text with fewer words than a shingle has its
whole word sequence as its one shingle; a null doc_id sorts before all others; repeated rows
share one component; rows that share a doc_id, or have none, are told apart by their texts; extra columns are ignored."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

PARTS, CHUNKS = 64, 14
RADIUS = 2 * CHUNKS - 1
#: Members of a key, and documents of a cluster, that one side of a comparison holds at most.
KEY_BLOCK, CLUSTER_BLOCK = 4096, 2048
#: Members from which a key is hot at any size, and counters by which a task finds such keys.
HOT_KEY, COUNTERS = 1 << 16, 1 << 20
_rng = np.random.default_rng(20240229)
_MUL = _rng.integers(1, 1 << 63, PARTS, dtype=np.uint64) * C.U64(2) + C.U64(1)
_ADD = _rng.integers(0, 1 << 63, PARTS, dtype=np.uint64)
_CUT = np.linspace(0, PARTS, CHUNKS + 1).astype(int)


def ascii_words(text: bytes | None) -> list[bytes]:
    return (text or b"").lower().split()


def signature(s: np.ndarray) -> np.ndarray:
    """16 bits of each component's minimum."""
    low = np.full(PARTS, np.iinfo(np.uint64).max, C.U64)
    for lo in range(0, len(s), 4096):
        part = s[lo : lo + 4096]
        for k in range(PARTS):
            low[k] = min(low[k], (part * _MUL[k] + _ADD[k]).min())
    return (C.mix(low) >> C.U64(48)).astype(np.uint16)


def chunk_keys(sig: np.ndarray) -> np.ndarray:
    """Keys of the rows of an (n, PARTS) matrix: each chunk with each component left out."""
    x = C.mix(sig.astype(C.U64) + (np.arange(PARTS, dtype=C.U64) << C.U64(16)) + C.U64(1))
    out = []
    for c in range(CHUNKS):
        lo, hi = _CUT[c], _CUT[c + 1]
        whole = x[:, lo:hi].sum(axis=1, dtype=C.U64)
        out += [C.mix(whole - x[:, i] + C.U64(i + 1)) for i in range(lo, hi)]
    return np.stack(out, axis=1)


def fewer(keys: np.ndarray, counts: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts by key, sorted; where there are more than ``most``, all less the next largest, so that a key loses at most a ``most``-th of the total."""
    k, at = np.unique(keys, return_inverse=True)
    n = np.bincount(at, counts, len(k)).astype(np.int64)
    if len(k) > most:
        n -= np.partition(n, len(n) - most - 1)[len(n) - most - 1]
        k, n = k[n > 0], n[n > 0]
    return k, n


def spread(n: int, near) -> list[tuple[int, int]]:
    """Tree edges of the graph on 0..n-1 whose neighbours of i among candidates c are c[near(i, c)]."""
    left, edges = np.arange(n), []
    while len(left) > 1:
        queue, left = [int(left[0])], left[1:]
        while queue and len(left):
            i = queue.pop()
            hit = near(i, left)
            if hit.any():
                found = left[hit].tolist()
                edges += [(i, j) for j in found]
                queue += found
                left = left[~hit]
    return edges


def _describe(width: int):
    def run(batches):
        for batch in batches:
            out = {c: [] for c in ("doc_id", "n", "k1", "k2", "sig")}
            for i, t in zip(C.ids(batch).tolist(), C.texts(batch)):
                s = C.shingles(ascii_words(t), width)
                key = xxhash.xxh3_128_intdigest(s.tobytes())
                out["doc_id"].append(i)
                out["n"].append(len(s))
                out["k1"].append((key & (1 << 64) - 1) - (1 << 63))
                out["k2"].append((key >> 64) - (1 << 63))
                out["sig"].append(signature(s).tobytes() if len(s) else None)
            yield pa.record_batch([pa.array(out["doc_id"], pa.int64()), pa.array(out["n"], pa.int64()), pa.array(out["k1"], pa.int64()), pa.array(out["k2"], pa.int64()), pa.array(out["sig"], pa.binary())], names=list(out))

    return run


def _keys(batches):
    """(keys, representatives) of (rep, sig) rows, 4096 rows at a time."""
    for batch in batches:
        rep = C.ids(batch, "rep")
        sig = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint16).reshape(-1, PARTS)
        for lo in range(0, len(rep), 4096):
            keys = chunk_keys(sig[lo : lo + 4096])
            yield keys.ravel(), np.repeat(rep[lo : lo + 4096], keys.shape[1])


def _frequent(most: int, share: float):
    """Counts of a task's keys, of which each loses at most a ``most``-th of all, but those below ``share`` of all."""

    def run(batches):
        keys, n = np.empty(0, C.U64), np.empty(0, np.int64)
        held, waiting, seen = [], 0, 0

        def merged():
            new = np.concatenate(held)
            return fewer(np.concatenate((keys, new)), np.concatenate((n, np.ones(len(new), np.int64))), most)

        for k, _ in _keys(batches):
            held.append(k)
            waiting += len(k)
            seen += len(k)
            if waiting >= most:
                keys, n = merged()
                held, waiting = [], 0
        if held:
            keys, n = merged()
        take = n >= share * seen
        yield pa.record_batch([pa.array(keys[take].view(np.int64)), pa.array(n[take])], names=["key", "n"])

    return run


def hot_keys(reps: DataFrame, rows: int, least: int, block: int, most: int = COUNTERS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys, and into how many blocks their members go: every key of at least ``least`` members, or 4 / ``most`` of all where that is more, and none
    of less than half as many, so at most ``most`` / 2 keys. A task's counts lose a quarter of that bound by ``most`` counters and one by ``share``."""
    total = rows * PARTS
    least = max(least, -(-4 * total // most))
    if total < least:
        return np.empty(0, C.U64), np.empty(0, np.int64)
    counts = reps.select("rep", "sig").mapInArrow(C.task(_frequent(most, least / (4 * total)), 10_000), "key long, n long")
    found = counts.groupBy("key").agg(F.sum("n").alias("n")).where(F.col("n") >= least / 2).toArrow()
    keys, n = found["key"].to_numpy().view(C.U64), found["n"].to_numpy()
    order = np.argsort(keys)
    return keys[order], np.maximum(-(-(n[order] + least // 2) // block), 2)


def _hot_sender(hot: np.ndarray, blocks: np.ndarray):
    """(gid, rep) of the members of hot keys: one row for each pair of blocks that the member's own is in."""

    def run(batches):
        for keys, who in _keys(batches):
            take = np.isin(keys, hot)
            keys, who = keys[take], who[take]
            m = blocks[np.searchsorted(hot, keys)]
            ends = np.cumsum(m - 1)
            for part in np.split(np.arange(len(keys)), np.flatnonzero(np.diff(ends // 500_000, prepend=0))):
                each = m[part] - 1
                at = np.repeat(part, each)
                own = (C.mix(who[at].view(C.U64)) % m[at].astype(C.U64)).astype(np.int64)
                other = np.arange(len(at)) - np.repeat(np.cumsum(each) - each, each)
                other += other >= own
                pair = (np.minimum(own, other) << 32 | np.maximum(own, other)).astype(C.U64)
                yield pa.record_batch([pa.array(C.mix(keys[at] + C.mix(pair + C.U64(1))).view(np.int64)), pa.array(who[at])], names=["gid", "rep"])

    return run


def _key_sender(buckets: list[int], hot: np.ndarray):
    """Every other key and its member, packed by bucket."""

    def run(batches):
        for keys, who in _keys(batches):
            if len(hot):
                cold = ~np.isin(keys, hot)
                keys, who = keys[cold], who[cold]
            to = (keys >> C.U64(32)) % C.U64(len(buckets))
            order = np.argsort(to, kind="stable")
            edges = np.searchsorted(to[order], np.arange(len(buckets) + 1, dtype=C.U64))
            rows = [(buckets[b], keys[o].tobytes(), who[o].tobytes()) for b in range(len(buckets)) if len(o := order[edges[b] : edges[b + 1]])]
            yield pa.record_batch([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.binary())], names=["bucket", "keys", "reps"])

    return run


def _grouper(block: int):
    """(gid, rep) of the keys that several representatives share; gid hashes the member list, or the key and a pair of
    blocks where a key has more than a block of members."""

    def run(batches):
        ks, rs = [], []
        for batch in batches:
            ks += [np.frombuffer(b, C.U64) for b in batch.column(1).to_pylist()]
            rs += [np.frombuffer(b, np.int64) for b in batch.column(2).to_pylist()]
        if not ks:
            return
        k, r = np.concatenate(ks), np.concatenate(rs)
        ks.clear(), rs.clear()
        order = np.lexsort((r, k))
        k, r = k[order], r[order]
        at = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
        n = np.diff(np.concatenate((at, [len(k)])))
        several = n > 1
        if not several.any():
            return
        take = np.repeat(several, n)
        k, r, n = k[take], r[take], n[several]
        at = np.cumsum(n) - n
        mixed = C.mix(r.view(C.U64))
        gid = np.add.reduceat(mixed, at) ^ C.mix(np.add.reduceat(C.mix(mixed + C.U64(5)), at))
        small = n <= block
        each = np.repeat(small, n)
        gids, reps = [np.repeat(gid, n)[each].view(np.int64)], [r[each]]
        for i in np.flatnonzero(~small).tolist():
            who = r[at[i] : at[i] + n[i]]
            m = -(-len(who) // block)
            parts = np.array_split(who, m)
            for a in range(m):
                for b in range(a + 1, m):
                    both = np.concatenate((parts[a], parts[b]))
                    gids.append(np.full(len(both), xxhash.xxh3_64_intdigest(f"{k[at[i]]}/{a}/{b}") - (1 << 63), np.int64))
                    reps.append(both)
        gids, reps = np.concatenate(gids), np.concatenate(reps)
        first = np.unique(np.stack((gids, reps), axis=1), axis=0)
        for lo in range(0, len(first), 500_000):
            yield pa.record_batch([pa.array(first[lo : lo + 500_000, 0]), pa.array(first[lo : lo + 500_000, 1])], names=["gid", "rep"])

    return run


def _by_group(batches, names: list[str]):
    """Lists of rows that share the first column, from rows sorted by it."""
    key, rows = None, []
    for batch in batches:
        for row in zip(*(batch.column(i).to_pylist() for i in range(len(names)))):
            if row[0] != key:
                if len(rows) > 1:
                    yield rows
                key, rows = row[0], []
            rows.append(row)
    if len(rows) > 1:
        yield rows


def _edge_batches(found):
    us, vs = [], []
    for u, v in found:
        us.append(u)
        vs.append(v)
        if len(us) >= 100_000:
            yield pa.record_batch([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])
            us, vs = [], []
    yield pa.record_batch([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])


def _near_signatures(batches):
    def found():
        for rows in _by_group(batches, ["gid", "rep", "sig"]):
            reps = [r[1] for r in rows]
            m = np.frombuffer(b"".join(r[2] for r in rows), np.uint16).reshape(-1, PARTS)
            for i, j in spread(len(reps), lambda i, left: (m[left] != m[i]).sum(axis=1) <= RADIUS):
                yield reps[i], reps[j]

    yield from _edge_batches(found())


def similar(sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Tree edges of the graph of sets with 100 * intersection >= percent * union."""
    size = np.array([len(s) for s in sets])
    _, code = np.unique(np.concatenate(sets), return_inverse=True)
    head = np.cumsum(size) - size
    mark = np.zeros(code.max() + 1, np.int64)

    def near(i, left):
        hit = np.zeros(len(left), bool)
        fits = (100 * np.minimum(size[left], size[i]) >= percent * np.maximum(size[left], size[i])).nonzero()[0]
        own = code[head[i] : head[i] + size[i]]
        mark[own] = 1
        for lo in range(0, len(fits), 512):
            c = left[fits[lo : lo + 512]]
            n = size[c]
            at = np.repeat(head[c] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            both = np.add.reduceat(mark[code[at]], np.cumsum(n) - n)
            hit[fits[lo : lo + 512]] = 100 * both >= percent * (n + size[i] - both)
        mark[own] = 0
        return hit

    return spread(len(sets), near)


def _confirmer(width: int, percent: int):
    def run(batches):
        def found():
            for rows in _by_group(batches, ["task", "doc_id", "text"]):
                who = [r[1] for r in rows]
                for i, j in similar([C.shingles(ascii_words(r[2]), width) for r in rows], percent):
                    yield who[i], who[j]

        yield from _edge_batches(found())

    def as_bytes(batches):
        for b in batches:
            yield pa.record_batch([b.column(0), b.column(1), b.column(2).cast(pa.binary())], names=["task", "doc_id", "text"])

    return lambda batches: run(as_bytes(batches))


def _components(keyed: DataFrame, width: int, percent: int, least: int = HOT_KEY, block: int = KEY_BLOCK) -> DataFrame:
    """(doc_id, n, component) of every row of (doc_id, text), where rows that share a doc_id share the text; no result depends on ``least`` and ``block``."""
    spark = keyed.sparkSession
    parts = C.exchange_width(keyed, 24 * PARTS)
    described = C.cut(keyed.mapInArrow(C.task(_describe(width)), "doc_id long, n long, k1 long, k2 long, sig binary"))
    classes = described.where("n > 0").groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.first("sig").alias("sig"))
    reps = C.cut(classes)
    buckets = C.partition_keys(spark, parts)
    many = reps.count()
    hot, blocks = hot_keys(reps, many, least, block)
    groups = reps.select("rep", "sig").mapInArrow(C.task(_key_sender(buckets, hot), 10_000), "bucket int, keys binary, reps binary").repartition(parts, "bucket").mapInArrow(C.task(_grouper(block)), "gid long, rep long")
    if len(hot):
        groups = groups.unionByName(reps.select("rep", "sig").mapInArrow(C.task(_hot_sender(hot, blocks), 10_000), "gid long, rep long"))
    groups = groups.distinct().join(reps.select("rep", "sig"), "rep").select("gid", "rep", "sig")
    candidates = groups.repartition(parts, "gid").sortWithinPartitions("gid", "rep").mapInArrow(C.task(_near_signatures, 10_000), "u long, v long")
    clusters = C.connected(spark, candidates)
    sizes = clusters.groupBy("root").agg(F.count("*").alias("n"), F.ceil(F.count("*") / CLUSTER_BLOCK).cast("int").alias("m"))
    member = C.join_counted(clusters, sizes, "root", many).withColumn("b", F.pmod(F.xxhash64("node"), F.col("m")).cast("int"))
    # one row per task; a cluster of m > 1 blocks has a task for each pair of them
    tasks = member.select("node", F.explode(F.when(F.col("m") == 1, F.array(F.xxhash64("root", F.lit(0), F.lit(0)))).otherwise(F.expr("transform(filter(sequence(0, m - 1), j -> j != b), j -> xxhash64(root, least(j, b), greatest(j, b)))"))).alias("task"))
    reptexts = keyed.join(clusters.select(F.col("node").alias("doc_id")), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    sets = reptexts.join(tasks.withColumnRenamed("node", "doc_id"), "doc_id").select("task", "doc_id", "text")
    links = sets.repartition(parts, "task").sortWithinPartitions("task", "doc_id").mapInArrow(C.task(_confirmer(width, percent)), "u long, v long")
    roots = C.connected(spark, links)
    named = reps.select("k1", "k2", "rep").join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").select("k1", "k2", F.coalesce("root", "rep").alias("component"))
    out = described.drop("sig").join(named, ["k1", "k2"], "left").withColumn("component", F.when(F.col("n") > 0, F.col("component")).otherwise(F.col("doc_id")))
    return out.select("doc_id", "n", "component")


def near_duplicates(docs: DataFrame, width: int = 4, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``docs``."""
    rows, ids = C.row_keys(docs.select("doc_id", "text"))
    out = _components(C.keyed_rows(rows), width, percent)
    if ids is not None:
        for c in ("doc_id", "component"):
            out = out.join(ids.withColumnRenamed(C.ROW, c), c).drop(c).withColumnRenamed("_id", c)
    return out.select(C.restored_id(), F.col("n").alias("n_shingles"), C.restored_id("component").alias("component_id"), (F.col("doc_id") == F.col("component")).alias("kept"))


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs``, all columns, but those of other texts than the first of their component; rows equal in doc_id and text stay together."""
    rows, _ = C.row_keys(docs)
    gone = C.cut(_components(C.keyed_rows(rows), width, percent).where("doc_id <> component").select(F.col("doc_id").alias(C.ROW)).distinct())
    return rows.join(gone, C.ROW, "left_anti").select(*docs.columns)


def op5_near_dup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(C.table(spark, sf_dir, "documents").select("doc_id", "text"), 4, 80)


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
sh AS (SELECT DISTINCT doc_id, array_to_string(ws[s:s+3], ' ') AS k FROM w, unnest(range(1, greatest(len(ws) - 2, 2))) AS u(s) WHERE len(ws) > 0),
n AS (SELECT doc_id, count(*) AS c FROM sh GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS i FROM sh a JOIN sh b ON a.k = b.k AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * i >= 80 * (nx.c + ny.c - i)),
e AS (SELECT x, y FROM l UNION SELECT y, x FROM l),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.y FROM r JOIN e ON e.x = r.b)
SELECT w.doc_id, CAST(coalesce(n.c, 0) AS BIGINT) AS n_shingles, CAST(m.c AS BIGINT) AS component_id, w.doc_id = m.c AS kept
FROM w LEFT JOIN n ON n.doc_id = w.doc_id JOIN (SELECT a, min(b) AS c FROM r GROUP BY a) m ON m.a = w.doc_id
"""
