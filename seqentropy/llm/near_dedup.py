"""Near-duplicate classes by a signature-coordinate inverted join.

A document's set is its distinct shingles of five words.  ``COORDINATES`` minima of independent hashes are its
signature; two sets of similarity 0.75 agree in 48 of 64 coordinates on average, and in fewer than ``MATCHES`` of them
with a chance of some 5 in a million.  Documents are posted under each (coordinate, value).  ``matches`` = 1 is the
exact mode: pairs are then missed only if no coordinate agrees at all (chance 4 in 10^39 at that similarity).

1. Documents with equal sets (128-bit digests) are one node, so that copies cost nothing further.  Nodes are numbered
   once, in a written table.
2. Postings that stand alone match nothing and leave.  Of the others, ordered by their frequency, a node keeps only as
   many as any partner with enough matches must meet one of (prefix filter): long lists, of passages that very many
   documents share, are skipped.
3. In each list all nodes are paired with its head (no list is expanded into all pairs); ``HEADS`` groups of coordinates
   choose different heads, so a node meets several members of its group.  Matches are counted over the whole signatures,
   the survivors are confirmed on the full sets, and confirmed links become components.
4. What is then left of a list is its outsiders: nodes outside its head's component.  They alone are compared with the
   list's nodes of other components, so no link between components is lost.  Short lists do so in a join; long ones are
   cut into blocks of bounded rows and bytes, outsiders against all, which first tell which rows have a partner with
   enough matches; those are compared on the full sets, and return only links that join components.

A list of n nodes with m outsiders costs 2 n m / ``BLOCK`` rows.  Nothing of all documents reaches the driver; every
step is written to the shared folder, so plans stay short.

Defined cases: null or empty texts, or texts of blanks, have empty sets and link with nothing; with fewer than five
words the whole sequence is the only shingle; rows with equal ids are linked if their sets are; null ids are null in
the result, rank last and are not kept, and a group of them alone has a null component; other columns are ignored.  A
row's key is its id and two hashes of its text, so the input may be read again in any order.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import cut, read, wrapped
from .graph import Forest, components

SHINGLE, COORDINATES, MATCHES, PERCENT = 5, 64, 32, 75
HEADS, SHORT_LIST, BLOCK, BLOCK_BYTES = 4, 48, 4096, 8 << 20
_LAST = 2**63 - 1
_SIGNED = "doc_id long, text_a long, text_b long, n_shingles long, set_high long, set_low long, keys array<long>"
_LOW = np.uint64(COORDINATES - 1)


def _column(batch, name: str):
    return batch.column(batch.schema.get_field_index(name))


def shingle_sets(texts: pa.Array) -> Iterator[np.ndarray]:
    """Each row's distinct shingle hashes, sorted."""
    for piece in K.pieces(texts):
        words = K.Words(piece, "space", True)
        h = words.hashes()
        g = K.grams(h, SHINGLE)
        for a, b in zip(words.bound[:-1].tolist(), words.bound[1:].tolist(), strict=True):
            if b - a >= SHINGLE:
                own = np.sort(g[a:b - SHINGLE + 1])
                yield own[np.concatenate([[True], own[1:] != own[:-1]])]
            else:
                yield K.grams(h[a:b], b - a) if b > a else np.zeros(0, np.uint64)


def signature(own: np.ndarray) -> np.ndarray:
    """The (coordinate, value) keys of a set: 64-bit hashes whose low bits are the coordinate."""
    if "minima" not in K._cache:
        K._cache["minima"] = (K.mix(np.arange(1, COORDINATES + 1, dtype=np.uint64)) | np.uint64(1), K.mix(np.arange(5001, 5001 + COORDINATES, dtype=np.uint64)), np.arange(COORDINATES, dtype=np.uint64))
    factor, shift, number = K._cache["minima"]
    least = np.full(COORDINATES, np.uint64(2**64 - 1))
    for k in range(0, len(own), 4096):
        np.minimum(least, (own[k:k + 4096][None, :] * factor[:, None] + shift[:, None]).min(1), out=least)
    return ((K.mix(least ^ shift) & ~_LOW) | number).view(np.int64)


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n = batch.num_rows
        size, high, low = (np.zeros(n, np.int64) for _ in range(3))
        keys = np.zeros((n, COORDINATES), np.int64)
        for r, own in enumerate(shingle_sets(_column(batch, "text"))):
            size[r] = len(own)
            if len(own):
                high[r] = np.add.reduce(K.mix(own)).view(np.int64)
                low[r] = np.add.reduce(K.mix(own ^ np.uint64(0x2545F4914F6CDD1D))).view(np.int64)
                keys[r] = signature(own)
        bounds = np.concatenate([[0], np.cumsum(np.where(size > 0, COORDINATES, 0))]).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(bounds), pa.array(keys[size > 0].ravel()))
        names = ["doc_id", "text_a", "text_b"]
        yield pa.RecordBatch.from_arrays([*(_column(batch, c).cast(pa.int64()) for c in names), pa.array(size), pa.array(high), pa.array(low), lists], [*names, "n_shingles", "set_high", "set_low", "keys"])


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs (u, v) whose full sets are similar enough; rows with equal u stand together, and its set is made once."""
    last, own = None, None
    for whole in batches:
        for k in range(0, whole.num_rows, 64):
            batch = whole.slice(k, 64)
            u, v, keep = _column(batch, "u"), _column(batch, "v"), []
            names = u.to_pylist()
            for r, b in enumerate(shingle_sets(_column(batch, "text_v"))):
                if names[r] != last:
                    last, own = names[r], next(shingle_sets(_column(batch, "text_u").slice(r, 1)))
                both = len(np.intersect1d(own, b, assume_unique=True))
                keep.append(both > 0 and 100 * both >= PERCENT * (len(own) + len(b) - both))
            yield pa.RecordBatch.from_arrays([u, v], ["u", "v"]).filter(pa.array(keep, pa.bool_()))


def _dealt(lists: DataFrame, blocks: F.Column) -> DataFrame:
    """Rows of lists (key, node, out, ...) dealt to groups (key, i, j): block i of the list's outsiders with block j of all its nodes.

    ``blocks`` is how many blocks an aggregate over some of a list's rows needs; a row of side 0 is an outsider that
    looks for partners, one of side 1 a possible partner.
    """
    many = lists.groupBy("key").agg(F.coalesce(blocks(F.col("out")), F.lit(1)).alias("n_i"), F.coalesce(blocks(F.lit(True)), F.lit(1)).alias("n_j"))
    each = lists.join(many, "key")
    i, j = (F.pmod(F.xxhash64("node", F.lit(k)), F.col(f"n_{x}")).cast("int") for k, x in enumerate("ij"))
    every = lambda x: F.explode(F.sequence(F.lit(0), F.col(f"n_{x}") - 1))
    seekers = each.where("out").withColumn("side", F.lit(0)).withColumn("i", i).withColumn("j", every("j"))
    return seekers.unionByName(each.withColumn("side", F.lit(1)).withColumn("j", j).withColumn("i", every("i"))).drop("n_i", "n_j")


def _by_rows(some: F.Column) -> F.Column:
    return F.ceil(F.sum(some.cast("long")) / BLOCK).cast("int")


def _by_bytes(some: F.Column) -> F.Column:
    return F.greatest(F.ceil(F.sum(F.when(some, F.col("size"))) * 8 / BLOCK_BYTES), F.ceil(F.sum(some.cast("long")) / BLOCK)).cast("int")


def _finder(matches: int):
    def run(table: pa.Table) -> pa.Table:
        """Rows with a partner of another component whose size and signature allow a link.

        A pair is looked at in one of its common lists only: that of the lowest coordinate which is in both prefixes.
        """
        root, side, size, mask, node = (table[k].to_numpy() for k in ("root", "side", "size", "mask", "node"))
        keys = table["keys"].combine_chunks().flatten().to_numpy().reshape(len(root), -1)
        bit = (mask.astype(np.uint64)[:, None] >> np.arange(COORDINATES, dtype=np.uint64)) & np.uint64(1) > 0
        coordinate = int(table["key"][0].as_py()) & (COORDINATES - 1)
        hit = np.zeros(len(root), bool)
        others = np.flatnonzero(side == 1)
        for a in np.flatnonzero(side == 0).tolist():
            at = others[(root[others] != root[a]) & (100 * np.minimum(size[others], size[a]) >= PERCENT * np.maximum(size[others], size[a]))]
            same = keys[at] == keys[a]
            some = same.sum(1) >= matches
            at, same = at[some], same[some]
            at = at[(same & bit[at] & bit[a]).argmax(1) == coordinate] if len(at) else at
            if len(at):
                hit[a] = True
                hit[at] = True
        out = np.zeros(len(root), bool)
        out[side == 0] = True
        return table.select(["key", "node", "root", "size"]).append_column("out", pa.array(out)).filter(pa.array(hit))

    return run


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [own.tobytes() for own in shingle_sets(_column(batch, "text"))]
        yield pa.RecordBatch.from_arrays([_column(batch, "node"), pa.array(sets, pa.binary())], ["node", "shingles"])


def _linker(table: pa.Table) -> pa.Table:
    """Links between different components, confirmed on the full sets: one for each pair of components that they join."""
    order = np.lexsort((table["node"].to_numpy(), table["side"].to_numpy()))
    node, root, side = (table[k].to_numpy()[order] for k in ("node", "root", "side"))
    own = table["shingles"].to_pylist()
    sets = [np.frombuffer(own[k], np.uint64) for k in order]
    first = int((side == 0).sum())
    right = sets[first:]
    out: list[tuple[int, int]] = []
    if first and right:
        size = np.array([len(x) for x in right])
        flat, of = np.concatenate(right), np.repeat(np.arange(len(right)), size)
        by = np.argsort(flat, kind="stable")
        flat, of = flat[by], of[by]
        forest = Forest()
        for a in range(first):
            lo, hi = np.searchsorted(flat, sets[a]), np.searchsorted(flat, sets[a], "right")
            width = hi - lo
            at = np.repeat(lo - (np.cumsum(width) - width), width) + np.arange(int(width.sum()))
            both = np.bincount(of[at], minlength=len(right))
            near = (100 * both >= PERCENT * (size + len(sets[a]) - both)) & (both > 0) & (root[first:] != root[a])
            out += [(int(node[a]), int(node[first + b])) for b in np.flatnonzero(near).tolist() if forest.join(int(root[a]), int(root[first + b]))]
    return pa.table({"u": pa.array([x for x, _ in out], pa.int64()), "v": pa.array([y for _, y in out], pa.int64())})


def _matched(pairs: DataFrame, known: DataFrame, matches: int) -> DataFrame:
    """Of the pairs (u, v), those whose sizes allow it and whose signatures agree often enough."""
    side = lambda x: known.select(F.col("node").alias(x), F.col("size").alias(f"n_{x}"), F.col("keys").alias(f"keys_{x}"))
    both = pairs.join(side("u"), "u").join(side("v"), "v")
    sizes = 100 * F.least("n_u", "n_v") >= PERCENT * F.greatest("n_u", "n_v")
    return both.where(sizes & (F.size(F.array_intersect("keys_u", "keys_v")) >= matches)).select("u", "v")


def _confirmed(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """pairs (u, v) of nodes; texts: node, text."""
    side = lambda x: texts.select(F.col("node").alias(x), F.col("text").alias(f"text_{x}"))
    return pairs.join(side("v"), "v").join(side("u"), "u").select("u", "v", "text_u", "text_v").mapInArrow(_confirm, "u long, v long")


def _keyed(text: F.Column) -> list[F.Column]:
    """A row's key: two hashes of its text (with the id they name it; rows that are equal in all three are interchangeable)."""
    return [F.xxhash64(text).alias("text_a"), F.xxhash64(F.lit("near"), text).alias("text_b")]


def near_classes(docs: DataFrame, matches: int = MATCHES) -> DataFrame:
    """One row per document: doc_id, text_a and text_b (hashes of its text), n_shingles, component_id, kept, and keeper: whether it is the document of its group that stays."""
    ids = docs.select("doc_id", "text", *_keyed(F.col("text")))
    signed = cut(ids.mapInArrow(_sign, _SIGNED), "signed")
    rank = F.coalesce("doc_id", F.lit(_LAST))
    sets = ["set_high", "set_low", "n_shingles"]
    classes = signed.where("n_shingles > 0").groupBy(*sets).agg(F.min(F.struct(rank.alias("rank"), "text_a", "text_b")).alias("first"), F.first("keys").alias("keys"))
    nodes = cut(classes.select(F.monotonically_increasing_id().alias("node"), *sets, "first", "keys"), "nodes")

    # lists, and each node's prefix of them
    postings = nodes.select("node", F.explode("keys").alias("key"))
    shared = postings.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    held = postings.join(shared, "key").groupBy("node").agg(F.array_sort(F.collect_list(F.struct("n", "key"))).alias("held")).where(F.size("held") >= matches)
    own = held.select("node", F.slice("held", F.lit(1), F.size("held") - matches + 1).alias("own"))
    coordinate = lambda key: key.bitwiseAND(F.lit(COORDINATES - 1)).cast("int")
    mask = F.aggregate("own", F.lit(0).cast("long"), lambda m, p: m.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), coordinate(p["key"]))))
    prefix = cut(own.select("node", mask.alias("mask"), F.explode("own").alias("p")).select("node", "mask", F.col("p.key").alias("key")), "prefix")
    known = cut(nodes.select("node", F.col("n_shingles").alias("size"), "first", "keys").join(prefix.select("node").distinct(), "node", "left_semi"), "known")
    at = ["rank", "text_a", "text_b"]
    named = known.select("node", "first.*")
    texts = cut(ids.select(rank.alias("rank"), "text_a", "text_b", "text").join(named, at).groupBy(*at, "node").agg(F.first("text").alias("text")).select("node", "text"), "texts")

    # each list's nodes against its head
    turn = F.xxhash64("node", F.pmod("key", F.lit(HEADS)))
    heads = prefix.groupBy("key").agg(F.min_by("node", turn).alias("head"), F.count("*").alias("n")).where("n > 1")
    stars = prefix.join(heads, "key").where("node <> head").select(F.least("head", "node").alias("u"), F.greatest("head", "node").alias("v")).distinct()
    links = cut(_confirmed(_matched(stars, known, matches), texts), "links")
    roots = components(links)

    # outsiders against their lists
    rooted = prefix.join(roots, "node", "left").select("key", "mask", "node", F.coalesce("root", "node").alias("root"))
    lists = rooted.groupBy("key").agg(F.count("*").alias("n"), F.min("root").alias("a"), F.max("root").alias("b"), F.min_by("root", turn).alias("main")).where("n > 2 and a <> b")
    rest = cut(rooted.join(lists.select("key", "n", "main"), "key").select("key", "mask", "n", "node", "root", (F.col("root") != F.col("main")).alias("out")), "rest")
    short = rest.where(F.col("n") <= SHORT_LIST)
    left = short.where("out").select("key", F.col("node").alias("a"), F.col("root").alias("root_a"))
    pairs = short.select("key", F.col("node").alias("b"), "root").join(left, "key").where("root <> root_a").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()
    again = cut(_confirmed(_matched(pairs, known, matches), texts), "links")
    long = rest.where(F.col("n") > SHORT_LIST).drop("n")
    if not long.isEmpty():
        signs = known.select("node", "size", "keys")
        dealt = _dealt(long.join(signs, "node"), _by_rows)
        flagged = cut(dealt.groupBy("key", "i", "j").applyInArrow(_finder(matches), "key long, node long, root long, size long, out boolean").groupBy("key", "node", "root", "size").agg(F.max("out").alias("out")), "flagged")
        full = texts.join(flagged.select("node").distinct(), "node", "left_semi").mapInArrow(_sets, "node long, shingles binary")
        far = _dealt(flagged, _by_bytes).join(full, "node").groupBy("key", "i", "j").applyInArrow(_linker, "u long, v long")
        again = again.unionAll(cut(far, "links"))
    if not again.isEmpty():
        roots = components(links.unionAll(again))

    rooted = nodes.select("node", *sets, F.col("first.rank").alias("rank"), "first").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    best = rooted.groupBy("root").agg(F.min("first").alias("best"))
    answer = rooted.select("root", *sets).join(best, "root").select(*sets, "best")
    out = signed.select("doc_id", "text_a", "text_b", *sets).join(answer, sets, "left")
    component = F.when(F.col("best").isNull(), F.col("doc_id")).when(F.col("best.rank") != _LAST, F.col("best.rank"))
    keeper = F.col("best").isNull() | (F.struct(rank.alias("rank"), "text_a", "text_b") == F.col("best"))
    return out.select("doc_id", "text_a", "text_b", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(False)).alias("kept"), keeper.alias("keeper"))


def op3_signature_join_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents``."""
    return near_classes(read(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "kept")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of each group one document stays, with all its columns.

    The document with the smallest id stays, of equal ids the one with the smaller hashes of its text, and of rows that
    are equal in both any one.  Documents without words link with nothing and all stay; null ids rank last; an empty
    table gives an empty one; columns of any names pass through.
    """
    keepers = cut(near_classes(docs).where("keeper and n_shingles > 0").groupBy(F.coalesce("doc_id", F.lit(_LAST)).alias("rank"), "text_a", "text_b").agg(F.count("*").alias("n")), "keepers")
    text = F.col("whole.text")
    words = F.coalesce(text.rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    whole = wrapped(docs).select("whole", words.alias("words"), F.coalesce(F.col("whole.doc_id"), F.lit(_LAST)).alias("rank"), *_keyed(text))
    at = ["rank", "text_a", "text_b"]
    stay = whole.where("words").join(keepers, at)
    once = stay.where("n > 1").groupBy(*at).agg(F.first("whole").alias("whole"))
    return whole.where("not words").select("whole").unionAll(stay.where("n = 1").select("whole")).unionAll(once.select("whole")).select("whole.*")


OP3_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS s
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM words WHERE len(w) > 0)),
sizes AS (SELECT doc_id, count(*) AS n FROM sets GROUP BY doc_id),
both_ AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS k FROM sets a JOIN sets b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS MATERIALIZED (SELECT u, v FROM both_ JOIN sizes x ON x.doc_id = u JOIN sizes y ON y.doc_id = v WHERE 100 * k >= 75 * (x.n + y.n - k)),
reach(doc_id, other) AS (SELECT doc_id, doc_id FROM documents UNION SELECT reach.doc_id, v FROM reach JOIN links ON links.u = reach.other),
best AS (SELECT doc_id, min(other) AS component_id FROM reach GROUP BY doc_id)
SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept
FROM best LEFT JOIN sizes USING (doc_id)
"""

register_pickle_by_value(sys.modules[__name__])
