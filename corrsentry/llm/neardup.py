"""Near-duplicate removal by MinHash with tensored banding, every link confirmed on full shingle sets.

Two small collections of minhashes give `t` half-keys each (`q` minhashes a half-key); every pair of a half-key from
the first and one from the second collection is a table key.  So t * t keys of 2 q minhashes come from 2 q t minhashes
instead of 2 q t * t.  Two texts of similarity s share a key with probability (1 - (1 - s**q)**t)**2: with q = 3 and
t = 11 that is 0.9992 at 0.8 and 0.99994 at 0.85.

Texts with the same shingle set are one node.  In each key's bucket every node is compared with the bucket's first
node by size (an exact bound) and by 64 one-bit minhashes (more than 22 of 64 differ: less than one in ten million for
pairs of similarity 0.8).  Nodes joined by such comparisons are a *family*.  Each node's most promising comparison is
verified on the full sets; verified links make components.  What a family has outside its largest component is then
compared with all of it on the full sets, in blocks, so a family that is linked costs nothing more and no group is
expanded into all pairs.  Last, members of a bucket that are in different families are compared by sketch and size, and
verified.  So every pair that shares a key is settled.

Edge cases: texts without words (null, empty) have no shingles and are linked with nothing; with fewer words than a
shingle the whole sequence is the only one; repeated rows and equal texts are linked; each row is a vertex of its own
text, so a repeated doc_id with another text is judged by that text; a null doc_id is linked like any other, and where
all of a group's ids are null its component_id is null and its rows are kept; an empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernel as K
from .common import even_join, forget, release, table, written

Q, T = 3, 11
SKETCH_LIMIT = 22


def minhashes(row: np.ndarray, h: np.ndarray, rows: int, k: int) -> np.ndarray:
    """(rows, k) minima of k linear maps of the hashes; rows without hashes have the largest value."""
    out = np.full((rows, k), np.iinfo(np.uint64).max, np.uint64)
    if not len(h):
        return out
    first = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
    own = row[first]
    factor, shift = K.mix(np.arange(1, k + 1, dtype=np.uint64)) | np.uint64(1), K.mix(np.arange(k + 1, 2 * k + 1, dtype=np.uint64))
    for j in range(k):
        out[own, j] = np.minimum.reduceat(h * factor[j] + shift[j], first)
    return out


def tensor_keys(m: np.ndarray, q: int = Q, t: int = T) -> np.ndarray:
    """(rows, t * t) table keys from (rows, 2 q t) minhashes."""
    half = np.zeros((len(m), 2 * t), np.uint64)
    for j in range(q):
        half = K.mix(half * np.uint64(K.BASE) + m[:, j :: q])
    a, b = half[:, :t], half[:, t:]
    salt = K.mix(np.arange(t * t, dtype=np.uint64)).reshape(1, t, t)
    return K.mix((K.mix(a)[:, :, None] * np.uint64(K.BASE) + b[:, None, :]) ^ salt).reshape(len(m), t * t)


def shingles(data: np.ndarray, offsets: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    return K.distinct(*K.row_grams(K.words(data, offsets, lower=True), size))


def _first(row: Column) -> Column:
    """Least (doc_id, tag) of a group; a null id comes last."""
    return F.min_by(row, F.struct(row["doc_id"].isNull(), row["doc_id"], row["tag"]))


def signatures(docs: DataFrame, size: int, q: int = Q, t: int = T) -> DataFrame:
    """doc_id, tag (hash of the text), n shingles, node (hash of the set), sketch, keys; a task gives the keys of a node once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(2)):
                row, h = shingles(data, offsets, size)
                at = K.by_row(row, hi - lo)
                total = np.zeros(len(h) + 1, np.uint64)
                np.cumsum(K.mix(h ^ np.uint64(0x5851F42D4C957F2D)), out=total[1:])
                n = np.diff(at)
                node = K.signed(K.mix((total[at[1:]] - total[at[:-1]]) + n.astype(np.uint64) * np.uint64(K.BASE)))
                new = []
                for i, v in enumerate(node.tolist()):
                    if n[i] and v not in seen:
                        seen.add(v)
                        new.append(i)
                if len(seen) > 2_000_000:
                    seen.clear()
                new_ = np.array(new, np.int64)
                mine = np.full(hi - lo, -1)
                mine[new_] = np.arange(len(new_))
                keep = mine[row] >= 0 if len(row) else np.zeros(0, bool)
                m = minhashes(mine[row[keep]], h[keep], len(new_), 2 * q * t)
                keys: list = [None] * (hi - lo)
                sketch: list = [None] * (hi - lo)
                for i, k, s in zip(new, K.signed(tensor_keys(m, q, t)), K.signed(np.packbits((m[:, :64] >> np.uint64(17) & np.uint64(1)).astype(np.uint8), axis=1).view(np.uint64).ravel() if len(new) else np.zeros(0, np.uint64))):
                    keys[i], sketch[i] = k, int(s)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), b.column(1).slice(lo, hi - lo), pa.array(n.astype(np.int64)), pa.array(node), pa.array(sketch, pa.int64()), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "tag", "n", "node", "sketch", "keys"])

    return docs.select("doc_id", F.xxhash64("text").alias("tag"), "text").mapInArrow(run, "doc_id long, tag long, n long, node long, sketch long, keys array<long>")


def _verified(pairs: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """The pairs (x, y) whose full sets are similar enough: 100 * intersection >= percent * union."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = []
            for lo in range(0, b.num_rows, 200):
                part = b.slice(lo, 200)
                both = pa.chunked_array([part.column(2), part.column(3)]).combine_chunks()
                n, counts, hashes = part.num_rows, np.zeros(2 * part.num_rows, np.int64), [[], []]
                for a, z, data, offsets in K.text_slices(both):
                    row, h = shingles(data, offsets, size)
                    counts[a:z] = np.bincount(row, minlength=z - a)
                    left = row + a < n
                    hashes[0] += [(row + a)[left], h[left]]
                    hashes[1] += [(row + a)[~left] - n, h[~left]]
                row, h = (np.concatenate([x for side in hashes for x in side[i::2]] or [np.zeros(0, t)]) for i, t in ((0, np.int64), (1, np.uint64)))
                order = np.lexsort((h, row))
                row, h = row[order], h[order]
                twice = (row[1:] == row[:-1]) & (h[1:] == h[:-1])
                inter = np.bincount(row[1:][twice], minlength=n)
                union = counts[:n] + counts[n:] - inter
                ok.append((100 * inter >= percent * union) & (union > 0))
            if ok:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["x", "y"]).filter(pa.array(np.concatenate(ok)))

    left = texts.select(F.col("node").alias("x"), F.col("text").alias("tx"))
    right = texts.select(F.col("node").alias("y"), F.col("text").alias("ty"))
    return pairs.select("x", "y").join(left, "x").join(right, "y").select("x", "y", "tx", "ty").mapInArrow(run, "x long, y long")


def linked_blocks(a: tuple[np.ndarray, np.ndarray, int], b: tuple[np.ndarray, np.ndarray, int], percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (i, j) of sets of a and of b that are similar enough; (row, hash, rows) of distinct shingles each.

    All intersections at once: a product of 0/1 matrices over the shingles that both sides have, some columns at a time;
    float32 holds the counts exactly."""
    (ra, ha, na), (rb, hb, nb) = a, b
    both = np.intersect1d(ha, hb)
    inter = np.zeros((na, nb), np.float32)
    parts = []
    for row, h in ((ra, ha), (rb, hb)):
        at = np.minimum(np.searchsorted(both, h), max(len(both) - 1, 0))
        ok = both[at] == h if len(both) else np.zeros(len(h), bool)
        parts.append((row[ok], at[ok]))
    for lo in range(0, len(both), 4096):
        m = []
        for (row, at), n in zip(parts, (na, nb)):
            here = (at >= lo) & (at < lo + 4096)
            x = np.zeros((n, min(4096, len(both) - lo)), np.float32)
            x[row[here], at[here] - lo] = 1
            m.append(x)
        inter += m[0] @ m[1].T
    size = np.bincount(ra, minlength=na)[:, None] + np.bincount(rb, minlength=nb)[None, :]
    return np.nonzero((100 * inter.astype(np.int64) >= percent * (size - inter.astype(np.int64))) & (inter > 0))


def _family_links(nodes: DataFrame, texts: DataFrame, size: int, percent: int, rows: int = 2000, shingles_: int = 1_000_000) -> DataFrame:
    """Links (x, y) between members of one family that are in different components.  nodes: node, fam, comp, n.

    The members outside the family's largest component are compared with all, in blocks of at most `rows` rows and about
    `shingles_` shingles: a task holds two blocks.  Only links come back, at most two for each row and component."""
    shares = nodes.groupBy("fam", "comp").agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("n"))
    blocks = F.greatest(F.ceil(F.col("c") / rows), F.ceil(F.col("n") / shingles_)).cast("int")
    fams = shares.groupBy("fam").agg(F.max_by("comp", F.struct("k", "comp")).alias("main"), F.count(F.lit(1)).alias("parts"), F.sum("k").alias("c"), F.sum("n").alias("n")).where("parts > 1")
    fams = written(fams.select("fam", "main", "c", blocks.alias("blocks")), "fams")
    own = written(even_join(nodes.select("node", "fam", "comp"), fams, ["fam"]).withColumn("b", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")), "parts")
    apart = own.where("comp <> main")
    # a family's blocks with members outside its largest component: one short list a family
    lists = written(apart.groupBy("fam").agg(F.collect_set("b").alias("places"), F.first("c").alias("c")), "lists")
    few = apart.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).join(texts, "node").select("fam", F.col("b").alias("i"), "j", "node", "comp", "text")
    all_ = even_join(own.select("fam", F.col("b").alias("j"), "node", "comp"), lists, ["fam"]).withColumn("i", F.explode("places")).join(texts, "node").select("fam", "i", "j", "node", "comp", "text")

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        sides = []
        for t in (a, b):
            row, h, at = [], [], 0
            for lo, hi, data, offsets in K.text_slices(t.column("text")):
                r, x = shingles(data, offsets, size)
                row.append(r + lo), h.append(x)
                at = hi
            sides.append((np.concatenate(row or [np.zeros(0, np.int64)]), np.concatenate(h or [np.zeros(0, np.uint64)]), at))
        i, j = linked_blocks(*sides, percent)
        x, y = a.column("node").to_numpy()[i], b.column("node").to_numpy()[j]
        cx, cy = a.column("comp").to_numpy()[i], b.column("comp").to_numpy()[j]
        new = cx != cy
        x, y, cx, cy = x[new], y[new], cx[new], cy[new]
        # one link between two components is as good as many
        first = np.unique(np.stack([np.minimum(cx, cy), np.maximum(cx, cy)], 1), axis=0, return_index=True)[1] if len(x) else np.zeros(0, np.int64)
        return pa.table({"x": pa.array(x[first], pa.int64()), "y": pa.array(y[first], pa.int64())})

    keys = ("fam", "i", "j")
    all_ = all_.toDF(*all_.columns)  # columns of its own: both sides come from one table
    return few.groupBy(*keys).cogroup(all_.groupBy(*keys)).applyInArrow(run, "x long, y long")


def components(edges: DataFrame) -> DataFrame:
    """(node, comp) of every node of the edges (x, y): comp is the smallest node that can be reached.

    Each round every vertex points to its least neighbour, pointers are doubled, and the graph is contracted; edges
    between different vertices shrink at least by half until none is left."""
    known = None
    while True:
        edges = written(edges.where("x <> y").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct(), "edges")
        if edges.isEmpty():
            break
        both = edges.select(F.col("x").alias("v"), F.col("y").alias("w")).unionByName(edges.select(F.col("y").alias("v"), F.col("x").alias("w")))
        p = both.groupBy("v").agg(F.min("w").alias("w")).select("v", F.least("v", "w").alias("p"))
        for _ in range(2):
            p = written(p, "pointers")
            up = p.select(F.col("v").alias("p"), F.col("p").alias("pp"))
            p = p.join(up, "p").select("v", F.col("pp").alias("p"))
        p = written(p, "pointers")
        known = p.select(F.col("v").alias("node"), F.col("p").alias("comp")) if known is None else written(known.join(p.withColumnRenamed("v", "comp"), "comp", "left").select("node", F.coalesce("p", "comp").alias("comp")), "known")
        edges = edges.join(p.select(F.col("v").alias("x"), F.col("p").alias("px")), "x").join(p.select(F.col("v").alias("y"), F.col("p").alias("py")), "y").select(F.col("px").alias("x"), F.col("py").alias("y"))
    if known is None:
        return edges.select(F.col("x").alias("node"), F.col("y").alias("comp"))
    return known


def _placed(docs: DataFrame, size: int, percent: int, q: int, t: int) -> DataFrame:
    """doc_id, tag, n and first: doc_id and tag of the row that stands for the row's component; null without shingles."""
    sig = written(signatures(docs, size, q, t), "signatures")
    nodes = sig.where("keys is not null").groupBy("node").agg(F.first("n").alias("n"), F.first("sketch").alias("sketch"))
    nodes = written(nodes, "nodes")
    keyed = sig.where("keys is not null").select("node", F.explode("keys").alias("key"))
    shared = written(keyed.groupBy("key").agg(F.min("node").alias("head"), F.max("node").alias("_tail"), F.count(F.lit(1)).alias("c")).where("head <> _tail").drop("_tail"), "shared")
    members = written(even_join(keyed, shared, ["key"]).drop("c").distinct(), "members")
    forget(shared)
    ends = lambda c: nodes.select(F.col("node").alias(c), F.col("n").alias(f"n{c}"), F.col("sketch").alias(f"s{c}"))
    gap = F.bit_count(F.col("sx").bitwiseXOR(F.col("sy")))
    alike = (F.least("nx", "ny") * 100 >= F.greatest("nx", "ny") * percent) & (gap <= SKETCH_LIMIT)
    stars = members.where("node <> head").select(F.col("node").alias("x"), F.col("head").alias("y")).distinct()
    stars = written(stars.join(ends("x"), "x").join(ends("y"), "y").where(alike).select("x", "y", gap.alias("gap")), "stars")
    first = stars.groupBy("x").agg(F.min_by("y", F.struct("gap", "y")).alias("y"))
    # a node's text is that of one of its rows, known by id and text: an id may be repeated with other texts, or null
    reps = sig.where("n > 0").groupBy("node").agg(_first(F.struct("doc_id", "tag")).alias("rep"))
    reps = reps.join(members.select("node").distinct(), "node", "left_semi").select("node", F.col("rep.doc_id").alias("_doc"), F.col("rep.tag").alias("_tag"))
    own = docs.select("doc_id", "text")
    texts = written(own.join(reps, (F.xxhash64(own["text"]) == F.col("_tag")) & own["doc_id"].eqNullSafe(F.col("_doc"))).dropDuplicates(["node"]).select("node", "text"), "texts")
    links = written(_verified(first, texts, size, percent), "links")
    # within families: members outside the largest component against all, in blocks
    comps, fams = components(links), components(stars).withColumnRenamed("comp", "fam")
    placed = fams.join(comps, "node", "left").join(nodes.select("node", "n"), "node").select("node", "fam", F.coalesce("comp", "node").alias("comp"), "n")
    placed = written(placed, "families")
    inner = written(_family_links(placed, texts, size, percent), "links")
    # across families: bucket members whose sketches are near, though no common head told so
    at = members.select("key", "node").join(placed.select("node", "fam"), "node", "left").select("key", "node", F.coalesce("fam", "node").alias("fam"))
    # one side leaves out the bucket's largest family: a great family with a few strangers is not joined with itself
    shares = at.groupBy("key", "fam").agg(F.count(F.lit(1)).alias("k"))
    mixed = written(shares.groupBy("key").agg(F.max_by("fam", F.struct("k", "fam")).alias("main"), F.count(F.lit(1)).alias("fams"), F.sum("k").alias("c")).where("fams > 1").select("key", "main", "c"), "buckets")
    at = written(even_join(at, mixed, ["key"]).drop("c").join(nodes, "node"), "mixed")
    side = lambda e: at.select("key", "main", F.col("node").alias(e), F.col("fam").alias(f"f{e}"), F.col("n").alias(f"n{e}"), F.col("sketch").alias(f"s{e}"))
    cross = even_join(side("y").drop("main"), side("x").where("fx <> main"), ["key"], sizes=mixed).where(((F.col("fy") == F.col("main")) | (F.col("fx") < F.col("fy"))) & alike)
    cross = cross.select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct()
    outer = written(_verified(cross, texts, size, percent), "links")
    comps = components(links.unionByName(inner).unionByName(outer))
    # a node may stand for a third of all rows, a component for a third of all nodes
    own = sig.where("n > 0").groupBy("node").agg(_first(F.struct("doc_id", "tag")).alias("first"), F.count(F.lit(1)).alias("rows"))
    named = written(own.join(comps, "node", "left").select("node", "first", "rows", F.coalesce("comp", "node").alias("comp")), "named")
    least = written(named.groupBy("comp").agg(_first(F.col("first")).alias("first"), F.count(F.lit(1)).alias("c")), "least")
    label = written(even_join(named.select("node", "rows", "comp"), least, ["comp"]).select("node", "first", F.col("rows").alias("c")), "label")
    told = even_join(sig.where("n > 0").select("doc_id", "tag", "n", "node"), label, ["node"]).select("doc_id", "tag", "n", "first")
    release(docs.sparkSession)
    return told.unionByName(sig.where("n = 0").select("doc_id", "tag", "n", F.lit(None).cast(label.schema["first"].dataType).alias("first")))


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80, q: int = Q, t: int = T) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest linked doc_id), kept."""
    component = F.when(F.col("n") > 0, F.col("first.doc_id")).otherwise(F.col("doc_id"))
    return _placed(docs, size, percent, q, t).select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"))


def drop_near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """One row of docs of each group of linked documents: the one with the smallest doc_id (a null id only if there is no
    other).  Rows with the same id and text are one document, rows with the same or no id and other texts are not."""
    seen = _placed(docs, size, percent, Q, T).where("n = 0 or (doc_id <=> first.doc_id and tag = first.tag)")
    seen = written(seen.select(F.col("doc_id").alias("_kept"), F.col("tag").alias("_tag")).distinct(), "kept")
    w = Window.partitionBy("doc_id", "_tag").orderBy(F.xxhash64(*[c for c in docs.columns]))
    kept = docs.join(seen, (F.xxhash64(docs["text"]) == seen["_tag"]) & docs["doc_id"].eqNullSafe(seen["_kept"])).drop("_kept")
    return kept.withColumn("_r", F.row_number().over(w)).where("_r = 1").drop("_r", "_tag")


def op7_minhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), size=2, percent=80)


#: The same rows by brute force on whole shingle sets; doc_id is taken as unique.
SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 1 THEN ws ELSE [ws[i] || ' ' || ws[i + 1] FOR i IN range(1, len(ws))] END) AS shingle FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
sets AS (SELECT doc_id, n, md5(string_agg(shingle, ' | ' ORDER BY shingle)) AS node FROM s JOIN n USING (doc_id) GROUP BY 1, 2),
nodes AS (SELECT node, min(doc_id) AS v, any_value(n) AS n FROM sets GROUP BY 1),
e AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b USING (shingle) JOIN nodes p ON p.v = a.doc_id JOIN nodes q ON q.v = b.doc_id
 WHERE a.doc_id < b.doc_id AND 100 * least(p.n, q.n) >= 80 * greatest(p.n, q.n) GROUP BY 1, 2),
links AS (SELECT x, y FROM e JOIN nodes p ON p.v = x JOIN nodes q ON q.v = y WHERE 100 * k >= 80 * (p.n + q.n - k)),
both_ways AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
reach AS (SELECT v AS a, v AS b FROM nodes UNION SELECT reach.a, both_ways.y FROM reach JOIN both_ways ON both_ways.x = reach.b),
comp AS (SELECT a AS v, min(b) AS component_id FROM reach GROUP BY 1)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(component_id, w.doc_id) AS component_id, coalesce(component_id, w.doc_id) = w.doc_id AS kept
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN sets USING (doc_id) LEFT JOIN nodes USING (node) LEFT JOIN comp USING (v)
"""
