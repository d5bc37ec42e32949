"""MinHash near-dedup with tensored banding: table keys are pairs of two smaller hash collections."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm.components import connected_components
from geocentra.llm.exchange import doc_table, slices
from geocentra.llm.plan import cut, cut_dealt, load, parts_for, text_bytes

PIECE_BYTES = 4 << 20
BUCKET_BYTES = 16 << 20
BLOCK_ROWS = 512


@dataclass(frozen=True)
class Banding:
    """Two collections of `half` rows of `rows` minima each give half * half table keys of 2 * rows minima.

    A pair of similarity s shares a key unless one of the collections has no equal row:
    it is missed with probability below 2 * (1 - s**rows)**half, 1e-5 at s = 0.8 as set
    here, for 48 minima where plain banding of the same 144 keys would compute 576.
    """

    half: int = 12
    rows: int = 2

    @property
    def minima(self) -> int:
        return 2 * self.half * self.rows

    def agreeing(self, percent: int) -> int:
        """How many minima must agree before full sets are compared.

        Of 48 minima a pair of similarity 0.8 has 38.4 +- 2.8 equal; 5.5 standard
        deviations less are asked for, which adds some 1e-6 to the share missed.
        """
        s = percent / 100
        return max(0, int(self.minima * s - 5.5 * (self.minima * s * (1 - s)) ** 0.5))


def shingle_sets(column: pa.Array, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, ascending, and the offsets of the texts into them.

    A text of fewer words than `width`, but not none, has its whole word sequence as its
    only shingle.
    """
    raw, offs = B.text_block(column)
    raw = B.LOWER[raw]
    starts, ends, by_text = B.words(raw, offs, B.NON_SPACE)
    h = B.word_hashes(raw, starts, ends)
    size = np.diff(by_text)
    count = np.maximum(size - width + 1, size > 0)
    first = np.cumsum(count) - count
    value = np.empty(int(count.sum()), B.U64)
    at = B.window_starts(by_text, width)
    if len(at):
        value[np.repeat(size >= width, count)] = B.window_hashes(h, width)[at]
    for n in range(1, width):
        short = np.flatnonzero(size == n)
        if len(short):
            value[first[short]] = B.mix(B.window_hashes(h, n)[by_text[short]] + B.U64(n))
    # One short sort a text costs less than one of all texts by two keys.
    for lo, k in zip(first.tolist(), count.tolist(), strict=True):
        if k > 1:
            value[lo : lo + k].sort()
    new = np.ones(len(value), bool)
    new[1:] = value[1:] != value[:-1]
    new[first[count > 0]] = True
    ends = np.concatenate(([0], np.cumsum(new)))
    return value[new], ends[np.concatenate((first, [len(value)]))]


def _sign(width: int, banding: Banding):
    """Per document: size and fingerprint of its shingle set, and its minima."""
    rng = np.random.default_rng(20240229)
    factor = (rng.integers(1, 1 << 62, banding.minima, dtype=np.uint64) << B.U64(1)) | B.U64(1)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in B.chunks(batches, "text", PIECE_BYTES):
            value, offs = shingle_sets(piece.column("text"), width)
            size = np.diff(offs)
            full = np.flatnonzero(size)
            first = offs[:-1][full]
            minima = np.zeros((piece.num_rows, banding.minima), np.uint32)
            prints = np.zeros((piece.num_rows, 2), B.U64)
            if len(full):
                product = np.empty_like(value)
                for j, f in enumerate(factor):
                    # The upper half of the least product is the least upper half.
                    minima[full, j] = (np.minimum.reduceat(np.multiply(value, f, out=product), first) >> B.U64(32)).astype(np.uint32)
                prints[full, 0] = np.add.reduceat(B.mix(value), first)
                prints[full, 1] = np.bitwise_xor.reduceat(B.mix(value ^ B.U64(0x5851F42D4C957F2D)), first)
            blob = minima.tobytes()
            step = 4 * banding.minima
            yield pa.RecordBatch.from_arrays(
                [
                    piece.column("id"),
                    piece.column("version"),
                    pa.array(size, pa.int64()),
                    pa.array(prints[:, 0].view(np.int64)),
                    pa.array(prints[:, 1].view(np.int64)),
                    pa.array([blob[i : i + step] for i in range(0, len(blob), step)], pa.binary()),
                ],
                names=["id", "version", "n", "p1", "p2", "minima"],
            )

    return run


def table_keys(minima: np.ndarray, banding: Banding) -> np.ndarray:
    """n x half*half keys: every row of the first collection with every row of the second."""
    n, half = len(minima), banding.half
    bands = minima.reshape(n, 2 * half, banding.rows).astype(B.U64)
    code = np.zeros((n, 2 * half), B.U64)
    for j in range(banding.rows):
        code = B.mix(code ^ (bands[:, :, j] + B.U64(j + 1)))
    code = B.mix(code + np.arange(2 * half, dtype=B.U64))
    return B.mix(code[:, :half, None] * B.U64(0x9FB21C651E98DF25) + code[:, None, half:]).reshape(n, half * half)


def _send_keys(banding: Banding, n_buckets: int):
    """Each key once a batch, with its smallest document; further documents of a key are linked on the spot.

    Blobs of three arrays are keys for their bucket; blobs of four are what a batch
    found by itself (members of keys, and candidate links) and pass through any bucket.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn = 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                piece = batch.slice(lo, 4096)
                ids = piece.column("id").to_numpy()
                order = np.argsort(ids)
                raw, _ = B.text_block(piece.column("minima"))
                minima = raw.view(np.uint32).reshape(len(ids), banding.minima)[order]
                ids = ids[order]
                key = table_keys(minima, banding)
                n_keys = key.shape[1]
                key = key.ravel()
                order = np.argsort(key, kind="stable")
                hs, doc = key[order], order // n_keys
                new = np.concatenate(([True], hs[1:] != hs[:-1]))
                part, blobs = [], []
                first = np.flatnonzero(new)
                for k, which in slices(B.bucket_of(hs[first], n_buckets), n_buckets):
                    at = first[which]
                    at = at[np.argsort(doc[at], kind="stable")]
                    f, c = doc_table(doc[at])
                    part.append(k)
                    blobs.append(B.pack(ids[doc[at[f]]], c.astype(np.int32), B.low_bytes(hs[at], 8)))
                many = ~new | np.concatenate((~new[1:], [False]))
                if many.any():
                    part.append(turn % n_buckets)
                    blobs.append(B.pack(*_groups(hs[many], ids[doc[many]])))
                    turn += 1
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "blob"])

    return run


def _groups(hs: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of keys in order, each with several documents, ascending: the (key, document) members, and links to the smallest."""
    new = np.ones(len(hs), bool)
    new[1:] = hs[1:] != hs[:-1]
    head = np.maximum.accumulate(np.where(new, np.arange(len(hs)), 0))
    pairs = np.stack((doc[head[~new]], doc[~new]), axis=1)
    pairs = np.unique(pairs[pairs[:, 0] != pairs[:, 1]], axis=0)
    return hs.view(np.int64), doc, np.ascontiguousarray(pairs[:, 0]), np.ascontiguousarray(pairs[:, 1])


def _padded(before: int, values: np.ndarray, after: int) -> pa.Array:
    return pa.concat_arrays([pa.nulls(before, pa.int64()), pa.array(values, pa.int64()), pa.nulls(after, pa.int64())])


def _meet(table: pa.Table) -> pa.Table:
    """One bucket of keys: links of each document to the smallest of its key, and the members of keys."""
    B.release()
    key, doc, found = [], [], []
    for blob in table.column("blob").to_pylist():
        arrays = B.unpack(blob)
        if len(arrays) == 4:
            found.append(arrays)
        else:
            ids, count, h = arrays
            key.append(B.from_bytes(h))
            doc.append(np.repeat(ids, count))
    if key:
        hs, doc = np.concatenate(key), np.concatenate(doc)
        order = np.argsort(hs)
        hs, doc = hs[order], doc[order]
        same = hs[1:] == hs[:-1]
        shared = np.concatenate((same, [False])) | np.concatenate(([False], same))
        hs, doc = hs[shared], doc[shared]
        order = np.lexsort((doc, hs))
        found.append(_groups(hs[order], doc[order]))
    key, doc, a, b = (np.concatenate(x) for x in zip(*found, strict=True)) if found else [np.zeros(0, np.int64)] * 4
    return pa.table({"key": _padded(0, key, len(a)), "a": _padded(0, np.concatenate((doc, a)), 0), "b": _padded(len(key), b, 0)})


def _verify(width: int, percent: int, agreeing: int):
    """Pairs of compressed texts whose full shingle sets are similar enough, of those whose minima agree often enough."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                piece = batch.slice(lo, 256)
                ma, mb = (B.text_block(piece.column(c))[0].view(np.uint32).reshape(piece.num_rows, -1) for c in ("ma", "mb"))
                piece = piece.filter(pa.array((ma == mb).sum(axis=1) >= agreeing))
                if not piece.num_rows:
                    continue
                texts = [B.unpack(x)[0] for side in ("za", "zb") for x in piece.column(side).to_pylist()]
                n = piece.num_rows
                offs = np.concatenate(([0], np.cumsum([len(t) for t in texts])))
                value, by_text = shingle_sets(B.strings(np.concatenate(texts), offs), width)
                size = np.diff(by_text)
                owner = np.repeat(np.arange(2 * n), size)
                pair = owner % n
                order = np.lexsort((value, pair))
                value, pair = value[order], pair[order]
                both = (value[1:] == value[:-1]) & (pair[1:] == pair[:-1])
                common = np.bincount(pair[1:][both], minlength=n)
                union = size[:n] + size[n:] - common
                ok = pa.array((100 * common >= percent * union) & (union > 0))
                yield piece.select(["a", "b"]).filter(ok)

    return run


def _compress(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for piece in B.chunks(batches, "text", PIECE_BYTES):
        raw, offs = B.text_block(piece.column("text"))
        z = [B.pack(raw[a:b]) for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
        yield pa.RecordBatch.from_arrays([piece.column("id"), piece.column("version"), pa.array(z, pa.binary())], names=["id", "version", "z"])


def _compare_blocks(width: int, percent: int, agreeing: int):
    """All pairs between two blocks of documents (or within one) that are not yet connected: a spanning set of their links.

    One document at a time is compared to all that lie in other components, have a
    fitting size and agree in enough minima; connected documents are not compared again.
    """

    def run(table: pa.Table) -> pa.Table:
        within = table.column("i")[0].as_py() == table.column("j")[0].as_py()
        side = (table.column("block").to_numpy() == table.column("j").to_numpy()).astype(bool)
        ids, component = table.column("id").to_numpy(), table.column("c").to_numpy().copy()
        minima = B.text_block(table.column("minima"))[0].view(np.uint32).reshape(len(ids), -1)
        values, sizes = [], []
        for blob in table.column("z").to_pylist():
            raw = B.unpack(blob)[0]
            value, offs = shingle_sets(B.strings(raw, np.array([0, len(raw)])), width)
            values.append(value)
            sizes.append(int(offs[-1]))
        size = np.array(sizes)
        _, code = np.unique(np.concatenate(values), return_inverse=True)
        offs = np.concatenate(([0], np.cumsum(size)))
        mark = np.zeros(int(code.max(initial=0)) + 1, bool)
        begun = component.copy()
        out: list[tuple[int, int, int, int]] = []
        for x in range(len(ids)) if within else np.flatnonzero(~side).tolist():
            other = component != component[x]
            if not within:
                other &= side
            other &= 100 * np.minimum(size, size[x]) >= percent * np.maximum(size, size[x])
            y = np.flatnonzero(other)
            y = y[(minima[y] == minima[x]).sum(axis=1) >= agreeing]
            if not len(y):
                continue
            mine = code[offs[x] : offs[x + 1]]
            mark[mine] = True
            common = np.add.reduceat(mark[code[B.ranges(offs[y], size[y])]].astype(np.int64), np.cumsum(size[y]) - size[y])
            mark[mine] = False
            for k in y[100 * common >= percent * (size[x] + size[y] - common)].tolist():
                if component[k] != component[x]:
                    out.append((int(ids[x]), int(ids[k]), int(begun[x]), int(begun[k])))
                    component[component == component[k]] = component[x]
        columns = zip(*out, strict=True) if out else [()] * 4
        return pa.table({n: pa.array(list(c), pa.int64()) for n, c in zip(("a", "b", "ca", "cb"), columns, strict=True)})

    return run


def _left_apart(seen: DataFrame, tried: DataFrame, component: DataFrame) -> DataFrame:
    """side, grp, id, c, blocks, block: the groups of documents whose candidates must still be compared with each other.

    What keys connect, directly or not, is a family. Of a family whose links so far leave
    several components either all documents are one group (side 0), or those of each key
    that has several components (side 1; equal sets of documents once), if that compares
    fewer pairs and sends no more texts.
    """
    family = connected_components(tried)
    ids = cut(family.select(F.col("node").alias("id"), F.col("component").alias("family")).join(component.select(F.col("node").alias("id"), "component"), "id", "left").select("id", "family", F.coalesce("component", "id").alias("c")))
    apart = cut(ids.groupBy("family").agg(F.count(F.lit(1)).alias("k"), F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi and k > 2").select("family", "k"))
    members = cut(seen.where("key is not null").select("key", F.col("a").alias("id")).distinct().join(ids, "id").select("key", "id", "family", "c"))
    marks = [F.bit_xor(F.xxhash64("id", F.lit(i))).alias(f"f{i}") for i in (1, 2)]
    by_key = members.groupBy("key").agg(F.count(F.lit(1)).alias("k"), F.min("c").alias("lo"), F.max("c").alias("hi"), F.min("family").alias("family"), *marks).where("lo <> hi and k > 2")
    keys = cut(by_key.groupBy("family", "k", "f1", "f2").agg(F.min("key").alias("key")).select("family", "k", "key"))
    size = F.col("k").cast("double")
    sent = size * F.ceil(F.col("k") / BLOCK_ROWS)
    cost = keys.groupBy("family").agg(F.sum(size * size).alias("pairs"), F.sum(sent).alias("texts"))
    way = cut(apart.join(cost, "family").select("family", "k", ((F.col("pairs") < size * size) & (F.col("texts") <= sent)).alias("by_keys")))
    chosen = way.where("not by_keys").select(F.lit(0).alias("side"), F.col("family").alias("grp"), "k")
    chosen = cut(chosen.unionByName(keys.join(way.where("by_keys").select("family"), "family").select(F.lit(1).alias("side"), F.col("key").alias("grp"), "k")))
    rows = ids.select(F.lit(0).alias("side"), F.col("family").alias("grp"), "id", "c").unionByName(members.select(F.lit(1).alias("side"), F.col("key").alias("grp"), "id", "c"))
    # Groups of a 4096th of all rows and more are 4096 at most: these go out whole, and no hot group is shuffled.
    many = max(BLOCK_ROWS, (ids.count() + members.count()) // 4096)
    hot = F.broadcast(chosen.where(F.col("k") >= many))
    rest = rows.join(hot.select("side", "grp"), ["side", "grp"], "left_anti").join(chosen.where(F.col("k") < many), ["side", "grp"])
    found = rows.join(hot, ["side", "grp"]).unionByName(rest).withColumn("blocks", F.ceil(F.col("k") / BLOCK_ROWS))
    return found.select("side", "grp", "id", "c", "blocks", F.pmod(F.xxhash64("id"), F.col("blocks")).alias("block"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, banding: Banding = Banding()) -> DataFrame:
    """Group documents whose sets of `width`-word shingles (A-Z folded) have a Jaccard similarity of percent/100 or more.

    Returns one row per id: id, n_shingles, component (the smallest id reachable over
    confirmed links, itself included), kept (id = component) and version (the hash of
    the text that was taken for this id).

    Null and empty texts have no shingles and link with nothing. Rows without an id
    are given back with their size, no component, and kept. Rows that repeat an id
    are taken as one document, the one with the largest shingle set (then fingerprint).
    An empty table gives no rows.

    Equal sets are one class from the start. Of a key's documents each is compared to
    the key's smallest. What these links leave apart is compared again, within its keys
    or among all that keys connect, whichever is less (see _left_apart), so no candidate
    is dropped. Groups are spread over pairs of blocks of BLOCK_ROWS; a pair of blocks
    emits only links that join components.
    """
    spark = docs.sparkSession
    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), text.alias("text"), F.xxhash64(text).alias("version"))
    size = text_bytes(rows, "text")
    signed = cut(rows.mapInArrow(_sign(width, banding), "id long, version long, n long, p1 long, p2 long, minima binary"))
    one = signed.where("id is not null").groupBy("id").agg(F.max(F.struct("n", "version", "p1", "p2", "minima")).alias("s")).select("id", "s.*")
    classes = one.where("n > 0").groupBy("n", "p1", "p2").agg(F.min(F.struct("id", "minima")).alias("s")).select("n", "p1", "p2", "s.*")
    n_buckets = parts_for(spark, size, BUCKET_BYTES)
    sent = classes.select("id", "minima").mapInArrow(_send_keys(banding, n_buckets), "bucket int, blob binary")
    seen = cut(sent.groupBy("bucket").applyInArrow(_meet, "key long, a long, b long"))
    # Texts of documents that share a key with another, partitioned by id once for all comparisons.
    involved = seen.select(F.col("a").alias("id")).unionByName(seen.where("b is not null").select(F.col("b").alias("id"))).distinct()
    chosen = one.join(involved, "id").select("id", "n", F.col("version").alias("chosen"), "minima")
    compressed = rows.where("id is not null").mapInArrow(_compress, "id long, version long, z binary").repartition(n_buckets, "id")
    texts = cut_dealt(compressed.join(chosen, "id").where("version = chosen").dropDuplicates(["id"]).select("id", "n", "minima", "z"))

    def confirmed(pairs: DataFrame) -> DataFrame:
        """Of candidate pairs (a, b), those that the full sets confirm."""
        left = pairs.join(texts.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("minima").alias("ma"), F.col("z").alias("za")), "a")
        both = left.join(texts.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("minima").alias("mb"), F.col("z").alias("zb")), "b")
        fits = both.where(100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
        return fits.select("a", "b", "ma", "mb", "za", "zb").mapInArrow(_verify(width, percent, banding.agreeing(percent)), "a long, b long")

    tried = cut(seen.where("key is null").select("a", "b").distinct())
    links = cut(confirmed(tried))
    component = connected_components(links)
    groups = _left_apart(seen, tried, component)
    paired = groups.join(texts, "id").select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other"))
    tasks = paired.select("side", "grp", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "id", "c", "minima", "z")
    more = cut(tasks.groupBy("side", "grp", "i", "j").applyInArrow(_compare_blocks(width, percent, banding.agreeing(percent)), "a long, b long, ca long, cb long"))
    heads = classes.select("n", "p1", "p2", F.col("id").alias("head")).join(component.select(F.col("node").alias("head"), "component"), "head", "left").select("n", "p1", "p2", F.coalesce("component", "head").alias("c"))
    # Later links join components: only these are connected once more.
    joined = connected_components(more.select(F.col("ca").alias("a"), F.col("cb").alias("b")))
    by_class = heads.join(joined.select(F.col("node").alias("c"), "component"), "c", "left").select("n", "p1", "p2", F.coalesce("component", "c").alias("component"))
    named = one.select("id", "version", "n", "p1", "p2").join(by_class, ["n", "p1", "p2"], "left")
    found = named.select("id", "version", F.col("n").alias("n_shingles"), F.coalesce("component", "id").alias("component"))
    nameless = signed.where("id is null").select("id", "version", F.col("n").alias("n_shingles"), F.lit(None).cast("long").alias("component"))
    return found.unionByName(nameless).withColumn("kept", F.coalesce(F.col("id") == F.col("component"), F.lit(True)))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = near_duplicates(load(spark, sf_dir, "documents"), width=2, percent=80)
    return got.select(F.col("id").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"), "kept")


ORACLE = r"""
WITH RECURSIVE t AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), []) AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i : i + 1], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 1, 1) + 1)) AS i FROM t WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
rare AS (SELECT g, row_number() OVER (ORDER BY count(*), g) AS rank FROM s GROUP BY g),
ordered AS (SELECT s.doc_id, s.g, n.n, row_number() OVER (PARTITION BY s.doc_id ORDER BY r.rank) AS k FROM s JOIN rare r USING (g) JOIN n USING (doc_id)),
prefix AS (SELECT doc_id, g, n FROM ordered WHERE k <= n - ceil(n * 0.8) + 1),
pairs AS (SELECT DISTINCT a.doc_id AS a, b.doc_id AS b, a.n AS na, b.n AS nb FROM prefix a JOIN prefix b ON a.g = b.g AND a.doc_id < b.doc_id WHERE least(a.n, b.n) * 100 >= greatest(a.n, b.n) * 80),
shared AS (SELECT p.a, p.b, p.na, p.nb, count(*) AS i FROM pairs p JOIN s x ON x.doc_id = p.a JOIN s y ON y.doc_id = p.b AND y.g = x.g GROUP BY ALL),
links AS (SELECT a, b FROM shared WHERE 100 * i >= 80 * (na + nb - i)),
both_ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT doc_id AS x, doc_id AS y FROM t UNION SELECT r.x, e.b FROM reach r JOIN both_ways e ON r.y = e.a),
least_of AS (SELECT x AS doc_id, min(y) AS component_id FROM reach GROUP BY x)
SELECT t.doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id, t.doc_id = c.component_id AS kept FROM t LEFT JOIN n USING (doc_id) JOIN least_of c USING (doc_id)
"""
