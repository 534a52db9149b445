"""Exact Jaccard join of word shingles by vertical partitioning of their global order.

1. One pass over the texts makes each document's set, its digest, and counts of all
   shingles in a table of hashed cells of fixed size. Documents with one set are one
   class from here on.
2. The global order puts shingles of rarer cells first. Two sets that link must share
   one of the first n - ceil(0.75 n) + 1 shingles of each. Shingles of these prefixes
   that two documents share give candidates, kept only if lengths and positions allow
   the overlap that a link takes.
3. Parity bits, a few for each shingle, prove for most unlike pairs that too many shingles
   differ. The rest is counted exactly: the global order is cut into fragments at fixed
   pivots, the parts of the two sets in each fragment are compared on their own, and the
   partial overlaps are summed for the pair.
4. First each class is compared with the least and the greatest of its prefix groups.
   What that links is contracted, and only pairs of different components remain to be
   compared. So a group of n near copies takes about n comparisons, and no link between
   different components is lost, however large a group is.

Defined cases: null texts and texts without words have an empty set and link with
nothing; a row with a null id gets its class's component but names none; rows that share
an id are one document, the set of the least digest counting; repeated rows agree; other
columns are not read. Ids are whole numbers; a column of other ids fails as it cannot be
cast. One very long text takes some forty bytes a word of one task's memory.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.llm.common import documents, forget, input_bytes, scratch, tidy, written
from vpatterns.llm.components import components
from vpatterns.llm.shingles import WordIds, mixed, shingle_set

PERCENT, WIDTH = 75, 5
#: Cells of the frequency table (log2, least and most), cells of one block of it, fragments of the order.
CELLS, MOST_CELLS, BLOCK, FRAGMENTS = 21, 24, 1 << 14, 8
#: Bytes of input for each cell, between these ends.
CELL_BYTES = 256
#: Sets whose share of all is above one in so many are met by a broadcast of that many rows at most.
HEAVY = 4096
#: Pairs of one set that a task takes in any case.
FEW_PAIRS = 256
#: A shingle's group is dealt out by salts where its cell has so many entries, and so many times the mean.
HOT_ENTRIES, HOT_TIMES, SALTS = 1_000_000, 64, 64
#: Bits of the filter that spares most texts outside any candidate pair a shuffle.
BITS = 1 << 23
FAN_IN = 64
#: Ratio of the ends of a range of sizes.
RANGE = 1.15

_SET = "kind int, doc_id long, n long, d1 long, d2 long, bits binary, block int, part int, counts binary"


def parity(s: np.ndarray) -> bytes:
    """Bit i: whether an odd number of shingles fall on place i of 4 to 8 places a shingle.

    Two sets' bits differ in no more places than the sets have different shingles, and
    bits of more places fold onto fewer, so sets of unlike sizes compare too.
    """
    places = 64
    while places < 4 * len(s):
        places *= 2
    return np.packbits(np.bincount((s & np.uint64(places - 1)).astype(np.int64), minlength=places) & 1).tobytes()


def _folded(x: np.ndarray, size: int) -> np.ndarray:
    while len(x) > size:
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    return x


def _differ(x: bytes, y: bytes) -> int:
    a, b = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
    size = min(len(a), len(b))
    return int(np.unpackbits(_folded(a, size) ^ _folded(b, size)).sum())


def _sets(docs: DataFrame, width: int, cells: int) -> DataFrame:
    """Rows of kind 0: doc_id, n, digest; of kind 1: a block of a partition's counts."""

    def step(batches):
        ids, total = WordIds(), np.zeros(1 << cells, np.int32)
        part = TaskContext.get().partitionId()
        empty = lambda k, n: pa.nulls(n, k)
        for batch in batches:
            n, d1, d2, bits = [], [], [], []
            pending, held = [], 0
            for at in range(0, batch.num_rows, 256):
                for text in batch.column(1)[at : at + 256].to_pylist():
                    s = shingle_set(text, ids, width)
                    digest = xxhash.xxh3_128_digest(s.tobytes())
                    n.append(len(s))
                    bits.append(parity(s))
                    d1.append(int.from_bytes(digest[:8], "little", signed=True))
                    d2.append(int.from_bytes(digest[8:], "little", signed=True))
                    pending.append(s)
                    held += len(s)
                    if held > 1_000_000:
                        total += np.bincount((np.concatenate(pending) >> np.uint64(64 - cells)).astype(np.int64), minlength=1 << cells).astype(np.int32)
                        pending, held = [], 0
            if pending:
                total += np.bincount((np.concatenate(pending) >> np.uint64(64 - cells)).astype(np.int64), minlength=1 << cells).astype(np.int32)
            m = batch.num_rows
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.zeros(m, np.int32)), batch.column(0), pa.array(n, pa.int64()), pa.array(d1, pa.int64()), pa.array(d2, pa.int64()), pa.array(bits, pa.binary()), empty(pa.int32(), m), empty(pa.int32(), m), empty(pa.binary(), m)],
                names=["kind", "doc_id", "n", "d1", "d2", "bits", "block", "part", "counts"],
            )
        blocks = [(i, _block_bytes(b)) for i, b in enumerate(total.reshape(-1, BLOCK)) if b.any()]
        m = len(blocks)
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.ones(m, np.int32)), *(empty(pa.int64(), m) for _ in range(4)), empty(pa.binary(), m), pa.array([i for i, _ in blocks], pa.int32()), pa.array(np.full(m, part, np.int32)), pa.array([b for _, b in blocks], pa.binary())],
            names=["kind", "doc_id", "n", "d1", "d2", "bits", "block", "part", "counts"],
        )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(step, _SET)


def _block_bytes(block: np.ndarray) -> bytes:
    """One block of cells: all of them, or places and counts where few are set."""
    at = np.flatnonzero(block)
    wide = np.int64 if block.max(initial=0) >= 1 << 31 else np.int32
    if 3 * len(at) < len(block):
        return b"s" + bytes([np.dtype(wide).itemsize]) + at.astype(np.uint16).tobytes() + block[at].astype(wide).tobytes()
    return b"d" + bytes([np.dtype(wide).itemsize]) + block.astype(wide).tobytes()


def _add_block(total: np.ndarray, raw: bytes) -> None:
    size = raw[1]
    kind = np.int64 if size == 8 else np.int32
    if raw[:1] == b"d":
        total += np.frombuffer(raw, kind, offset=2)
        return
    n = (len(raw) - 2) // (2 + size)
    total[np.frombuffer(raw, np.uint16, n, 2).astype(np.int64)] += np.frombuffer(raw[2 + 2 * n :], kind)


def _added(blocks: DataFrame, parts: int, cells: int) -> np.ndarray:
    """The sum of all partitions' cells; each group adds FAN_IN blocks at most."""

    def add(key, t):
        total = np.zeros(BLOCK, np.int64)
        for x in t.column("counts"):
            _add_block(total, x.as_py())
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "part": pa.array([key[1].as_py()], pa.int32()), "counts": pa.array([_block_bytes(total)], pa.binary())})

    while True:
        blocks = blocks.withColumn("part", F.expr(f"cast(part div {FAN_IN} as int)"))
        blocks = blocks.groupBy("block", "part").applyInArrow(add, "block int, part int, counts binary")
        parts = -(-parts // FAN_IN)
        if parts <= 1:
            break
    out = np.zeros(1 << cells, np.int64)
    for batch in blocks.select("block", "counts").toArrow().to_batches():
        for i, raw in zip(batch.column(0).to_pylist(), batch.column(1)):
            _add_block(out[i * BLOCK : (i + 1) * BLOCK], raw.as_py())
    return out


def cells_for(docs: DataFrame) -> int:
    """log2 of the number of cells: a fixed number of input bytes each, between the two ends.

    The order of shingles may be any, so this changes only speed.
    """
    return int(min(MOST_CELLS, max(CELLS, math.ceil(math.log2(input_bytes(docs) / CELL_BYTES)))))


def pivots(levels: np.ndarray, counts: np.ndarray, fragments: int) -> np.ndarray:
    """Keys at which the global order is cut, so that fragments hold like numbers of shingles."""
    weight = np.bincount(levels, counts, minlength=64).astype(float)
    ends, total = np.cumsum(weight), max(1.0, weight.sum())
    out = []
    for i in range(1, fragments):
        goal = total * i / fragments
        level = int(min(np.searchsorted(ends, goal), 63))
        part = (goal - (ends[level] - weight[level])) / max(1.0, weight[level])
        out.append(level << 56 | int(min(max(part, 0.0), 1.0) * ((1 << 56) - 1)))
    return np.array(out, np.uint64)


def _keys(s: np.ndarray, levels: np.ndarray, cells: int) -> np.ndarray:
    """Places in the global order: the cell's level, then the number itself."""
    return levels[(s >> np.uint64(64 - cells)).astype(np.int64)].astype(np.uint64) << np.uint64(56) | s >> np.uint64(8)


def _prefixes(docs: DataFrame, levels, copies, width: int, percent: int, cells: int, hot_level: int) -> DataFrame:
    """token, doc_id, n, place, copy, hot, salt: each set's prefix; ``copy`` if it may not stand
    for its class, ``hot`` if the shingle's cell has so many entries that its group is dealt out."""

    def step(batches):
        ids, table = WordIds(), levels.value
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                token, node, packed = [], [], []
                maybe = _hit(copies.value, batch.column(2)[at : at + 512].to_numpy())
                for key, text, c in zip(batch.column(0)[at : at + 512].to_pylist(), batch.column(1)[at : at + 512].to_pylist(), maybe):
                    s = shingle_set(text, ids, width)
                    n = len(s)
                    if not n or key is None:
                        continue
                    p = n - -(-percent * n // 100) + 1
                    order = np.argsort(_keys(s, table, cells), kind="stable")[:p]
                    token.append(s[order])
                    node.append(np.full(p, key, np.int64))
                    hot = (table[(s[order] >> np.uint64(64 - cells)).astype(np.int64)] >= hot_level).astype(np.int64)
                    packed.append(n << 33 | np.arange(p, dtype=np.int64) << 2 | hot << 1 | int(c))
                if token:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in ([t.view(np.int64) for t in token], node, packed)], names=["token", "doc_id", "packed"])

    rows = docs.select(F.col("doc_id").cast("long"), "text").withColumn("h", F.pmod(F.xxhash64("doc_id"), F.lit(BITS)))
    dealt = rows.mapInArrow(step, "token long, doc_id long, packed long")  # four numbers travel as one
    if hot_level <= 63:
        dealt = dealt.withColumn("salt", F.when(F.expr("packed & 2L = 2"), F.pmod(F.xxhash64("doc_id"), F.lit(SALTS))).otherwise(0)).repartition("token", "salt").drop("salt")
    else:
        dealt = dealt.repartition("token")
    return dealt.selectExpr("token", "doc_id", "cast(shiftright(packed, 33) as int) as n", "cast(shiftright(packed & 8589934591L, 2) as int) as place", "packed & 1L = 1 as copy", "packed & 2L = 2 as hot")


def _of_group(rows: DataFrame, facts: dict, hot: bool, key: str) -> DataFrame:
    """rows with facts (aggregates by token, name ``c`` being the count) of groups of two or more.

    Groups of hot shingles are added up in parts and their facts sent back by salts, so no
    task sees such a group whole; the others are windows.
    """
    over = W.partitionBy("token")
    plain = rows.where("not hot") if hot else rows
    out = plain.withColumns({k: f.over(over) for k, f in facts.items()}).where("c > 1")
    if not hot:
        return out
    some = rows.where("hot")
    each = some.groupBy("token").agg(*[f.alias(k) for k, f in facts.items()]).where("c > 1")
    each = each.withColumn("salt", F.explode(F.expr(f"sequence(0L, {SALTS - 1}L)")))
    met = some.withColumn("salt", F.pmod(F.xxhash64(key), F.lit(SALTS))).join(each, ["token", "salt"]).drop("salt")
    return out.unionByName(met.select(*out.columns))


def _spans(percent: int) -> tuple:
    """(early, least, most): whether a set may be the smaller of a pair that shares this
    place, and the sizes of smaller sets that it may be the larger for."""
    n, place = F.col("n"), F.col("place")
    early = (n - place) * (100 + percent) >= 2 * percent * n
    least = F.ceil(percent * n / 100.0 - 1e-9)
    most = F.least(n, F.floor((100 + percent) * (n - place) / percent) - n)
    return early, least, most


def _allowed(percent: int) -> str:
    """A link's overlap may still be reached by sizes and by places in the prefixes."""
    need = f"ceil({percent} * (na + nb) / {100 + percent}.0D - 1e-9)"
    return f"100 * least(na, nb) >= {percent} * greatest(na, nb) and least(na - pa, nb - pb) >= {need}"


def _fragments(rows: DataFrame, levels, cuts: np.ndarray, width: int, cells: int) -> DataFrame:
    """a, b, na, nb, fragment, body: the text's shingles in each fragment, for each of its pairs."""
    names = ["a", "b", "na", "nb", "fragment", "body"]

    def step(batches):
        ids, table, last, parts = WordIds(), levels.value, object(), []
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                some = batch.slice(at, 128)
                out = []
                for key, text, *pair in zip(*(some.column(i).to_pylist() for i in range(6))):
                    if key != last:  # a text's pairs follow one another
                        s = shingle_set(text, ids, width)
                        which = np.searchsorted(cuts, _keys(s, table, cells), "right")
                        parts, last = [(int(f), s[which == f].tobytes()) for f in np.unique(which)], key
                    out += [(*pair, f, body) for f, body in parts]
                kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*out)) or [()] * 6, kinds)], names=names)

    return rows.select("doc_id", "text", "a", "b", "na", "nb").mapInArrow(step, "a long, b long, na int, nb int, fragment int, body binary")


def verified(fragments: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The pairs that link: each fragment's overlap is counted on its own, and summed for the pair."""

    def step(batches):
        for batch in batches:
            part = [len(np.intersect1d(*(np.frombuffer(x, np.uint64) for x in two), assume_unique=True)) for two in batch.column(4).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(part, pa.int32())], names=["a", "b", "na", "nb", "part"])

    met = fragments.repartition("a", "b").groupBy("a", "b", "na", "nb", "fragment").agg(F.collect_list("body").alias("two")).where("size(two) = 2")
    overlaps = met.select("a", "b", "na", "nb", "two").mapInArrow(step, "a long, b long, na int, nb int, part int")
    summed = overlaps.groupBy("a", "b", "na", "nb").agg(F.sum("part").alias("common"))
    return summed.where(f"{100 + percent} * common >= {percent} * (na + nb)").select("a", "b")


def _hopeful(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs whose parity bits do not prove that too many shingles differ."""
    shared = _id_filter(_ends(pairs))

    def needed(batches):
        for batch in batches:
            yield batch.filter(pa.array(_hit(shared.value, batch.column(2).to_numpy()))).select(["doc_id", "bits"])

    def step(batches):
        for batch in batches:
            columns = [batch.column(i).to_pylist() for i in range(6)]
            most = [na + nb - 2 * -(-percent * (na + nb) // (100 + percent)) for na, nb in zip(columns[2], columns[3])]
            keep = [_differ(x, y) <= m for x, y, m in zip(columns[4], columns[5], most)]
            yield batch.filter(pa.array(keep, pa.bool_())).select(["a", "b", "na", "nb"])

    rows = sets.where("kind = 0 and doc_id is not null").select("doc_id", "bits").withColumn("h", F.pmod(F.xxhash64("doc_id"), F.lit(BITS)))
    bits = rows.mapInArrow(needed, "doc_id long, bits binary")
    both = pairs.join(bits.select(F.col("doc_id").alias("a"), F.col("bits").alias("x")), "a").join(bits.select(F.col("doc_id").alias("b"), F.col("bits").alias("y")), "b")
    return both.select("a", "b", "na", "nb", "x", "y").mapInArrow(step, "a long, b long, na int, nb int").distinct()


def _dealt_pairs(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """doc_id, text, a, b, na, nb: each text beside its pairs.

    A set that is the middle of a large star has very many pairs. Such sets, fewer than
    HEAVY of them by the way they are chosen, come in copies that share the pairs.
    """
    of_text = pairs.select("*", F.explode(F.array("a", "b")).alias("doc_id"))
    each = max(FEW_PAIRS, 2 * pairs.count() // HEAVY)
    many = of_text.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > each)
    many = F.broadcast(many.select("doc_id", F.ceil(F.col("n") / each).alias("copies")))
    copies = F.coalesce("copies", F.lit(1).cast("long"))
    of_text = of_text.join(many, "doc_id", "left").withColumn("copy", F.pmod(F.xxhash64("a", "b"), copies)).drop("copies")
    texts = texts.join(many, "doc_id", "left").select("doc_id", "text", F.explode(F.sequence(F.lit(0).cast("long"), copies - 1)).alias("copy"))
    return texts.join(of_text, ["doc_id", "copy"])


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()


def _id_filter(ids: DataFrame):
    """A filter of fixed size over doc_id; when it is full it lets everything through."""
    place = F.pmod(F.xxhash64("doc_id"), F.lit(BITS))
    words = ids.select(place.alias("h")).groupBy(F.expr("cast(h div 64 as int)").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(h % 64 as int))")).alias("m")).toArrow()
    table = np.zeros(BITS // 64, np.int64)
    table[words.column("w").to_numpy()] = words.column("m").to_numpy()
    return ids.sparkSession.sparkContext.broadcast(table)


def _hit(table: np.ndarray, h: np.ndarray) -> np.ndarray:
    return (table[h >> 6] >> (h & 63) & 1).astype(bool)


def _texts_of(nodes: DataFrame, docs: DataFrame) -> DataFrame:
    """doc_id, text of the named nodes; a filter of fixed size goes before the shuffle."""
    shared = _id_filter(nodes)

    def step(batches):
        for batch in batches:
            yield batch.filter(pa.array(_hit(shared.value, batch.column(2).to_numpy()))).select(["doc_id", "text"])

    rows = docs.select(F.col("doc_id").cast("long"), "text").where("doc_id is not null")
    rows = rows.withColumn("h", F.pmod(F.xxhash64("doc_id"), F.lit(BITS))).mapInArrow(step, "doc_id long, text string")
    return rows.join(nodes, "doc_id", "left_semi")


def _members(sets: DataFrame) -> DataFrame:
    """doc_id, n_shingles, node: node is the least id with the same set, null where that is empty.

    A set that holds more than one in HEAVY of all rows is met by a broadcast (there are
    fewer than HEAVY of them), so its rows stay where they are.
    """
    own = sets.where("kind = 0").select("doc_id", F.col("n").alias("n_shingles"), "d1", "d2")
    full = own.where("n_shingles > 0")
    of_set = full.groupBy("d1", "d2").agg(F.min("doc_id").alias("node"), F.count(F.lit(1)).alias("rows"))
    least = max(1, own.count() // HEAVY)
    heavy = F.broadcast(of_set.where(F.col("rows") > least).select("d1", "d2", "node"))
    light = of_set.where(F.col("rows") <= least).select("d1", "d2", "node")
    out = full.join(heavy, ["d1", "d2"]).unionByName(full.join(heavy, ["d1", "d2"], "left_anti").join(light, ["d1", "d2"]))
    return out.select("doc_id", "n_shingles", "node").unionByName(own.where("n_shingles = 0").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("node")))


def classes(docs: DataFrame, percent: int = PERCENT, width: int = WIDTH, cells: int | None = None, fragments: int = FRAGMENTS, hot_entries: int = HOT_ENTRIES) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of docs (columns doc_id, text)."""
    spark = docs.sparkSession
    folder = scratch(spark)
    cells = cells_for(docs) if cells is None else cells
    sets = written(_sets(docs, width, cells), folder, "sets")
    parts = max(1, docs.rdd.getNumPartitions())
    counts = _added(sets.where("kind = 1").select("block", "part", "counts"), parts, cells)
    level = np.floor(np.log2(counts + 1)).astype(np.uint8)
    hot_level = math.ceil(math.log2(max(hot_entries, HOT_TIMES * counts.mean()) + 1))
    hot = bool(level.max(initial=0) >= hot_level)
    hot_level = hot_level if hot else 64
    levels = spark.sparkContext.broadcast(level)
    cuts = pivots(level.astype(np.int64), counts, fragments)
    del counts
    member = written(_members(sets), folder, "members")

    # Prefix shingles that a smaller and a larger set may share, copies of one set taken as one.
    early, least, most = _spans(percent)
    smaller = F.when(early, F.col("n"))
    count = F.count(F.lit(1))
    to_node = member.where("node is not null").groupBy("doc_id").agg(F.min("node").alias("node"))
    copies = _id_filter(to_node.where("doc_id <> node"))
    rows = _prefixes(docs, levels, copies, width, percent, cells, hot_level)
    if hot:
        rows = written(rows, folder, "all_prefixes")
    rows = _of_group(rows, {"c": count, "lo": F.min(smaller), "hi": F.max(smaller)}, hot, "doc_id")
    rows = written(rows.where(early | ((least <= F.col("hi")) & (most >= F.col("lo")))).drop("c", "lo", "hi"), folder, "prefixes")
    copies.destroy()
    tidy(spark)
    stands = rows.where("copy").join(to_node.where("doc_id = node").select("doc_id"), "doc_id", "left_semi")
    hits = rows.where("not copy").unionByName(stands.select(*rows.columns))
    hits = hits if hot else hits.repartition("token")
    hits = hits.groupBy("token", F.col("doc_id").alias("node")).agg(F.min("n").alias("n"), F.min("place").alias("place"), F.first("hot").alias("hot"))
    hits = written(hits, folder, "all_hits") if hot else hits
    at = F.struct("node", "n", "place")
    hits = written(_of_group(hits, {"c": count, "low": F.min(at), "high": F.max(at)}, hot, "node"), folder, "hits")
    for name in ("prefixes", "all_prefixes", "all_hits"):
        forget(spark, folder, name)
    tidy(spark)

    # Stars: everyone against the least and the greatest of its groups.
    star = lambda end: hits.where(f"node <> {end}.node").select(F.least("node", f"{end}.node").alias("a"), F.greatest("node", f"{end}.node").alias("b"), F.expr(f"if(node < {end}.node, n, {end}.n)").alias("na"), F.expr(f"if(node < {end}.node, {end}.n, n)").alias("nb"), F.expr(f"if(node < {end}.node, place, {end}.place)").alias("pa"), F.expr(f"if(node < {end}.node, {end}.place, place)").alias("pb"))
    stars = written(star("low").unionByName(star("high")).where(_allowed(percent)).select("a", "b", "na", "nb").distinct(), folder, "stars")

    def linked(pairs: DataFrame, name: str) -> DataFrame:
        near = written(_hopeful(pairs, sets, percent), folder, f"{name}_near")
        texts = _texts_of(_ends(near), docs).dropDuplicates(["doc_id"])
        found = written(verified(_fragments(_dealt_pairs(texts, near), levels, cuts, width, cells), percent), folder, name)
        tidy(spark)
        return found

    links = linked(stars, "links1")
    final = components(links, folder, "c1")

    # What is left: members of one group in different components. The larger of two sets
    # looks for the smaller among those that have the shingle early enough, by ranges of the
    # sizes that its own place still allows; what has no such partner goes before that.
    known = hits.select("token", "node", "n", "place", "hot").join(final, "node", "left").withColumn("component", F.coalesce("component", "node"))
    known = written(known, folder, "placed") if hot else known
    component = F.when(early, F.col("component"))
    known = _of_group(known, {"c": count, "lo": F.min(smaller), "hi": F.max(smaller), "one": F.min(component), "other": F.max(component), "c1": F.min("component"), "c2": F.max("component")}, hot, "node")
    larger = (least <= F.col("hi")) & (most >= F.col("lo")) & ((F.col("one") != F.col("component")) | (F.col("other") != F.col("component")))
    known = known.where("c1 < c2").where(early | larger).withColumns({"larger": larger, "early": early})
    known = written(known.drop("c", "lo", "hi", "one", "other", "c1", "c2", "hot"), folder, "known")
    forget(spark, folder, "placed")
    if known.limit(1).count():
        range_of = lambda n: F.floor(F.log(n.cast("double")) / math.log(RANGE))
        x = known.where("larger").withColumn("size", F.explode(F.sequence(range_of(least), range_of(most))))
        x = x.select("token", "size", F.col("node").alias("u"), F.col("n").alias("na"), F.col("place").alias("pa"), F.col("component").alias("ca"))
        y = known.where("early").select("token", range_of(F.col("n")).alias("size"), F.col("node").alias("v"), F.col("n").alias("nb"), F.col("place").alias("pb"), F.col("component").alias("cb"))
        groups = y.groupBy("token", "size", "cb").agg(F.min("nb").alias("least"))
        near = x.join(groups, ["token", "size"]).where("ca <> cb and na >= least")
        rest = near.join(y, ["token", "size", "cb"]).where(_allowed(percent) + " and (na > nb or (na = nb and u > v))")
        flip = "u > v"
        rest = rest.select(F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b"), F.expr(f"if({flip}, nb, na)").alias("na"), F.expr(f"if({flip}, na, nb)").alias("nb")).distinct()
        rest = written(rest.join(stars.select("a", "b"), ["a", "b"], "left_anti"), folder, "rest")
        if rest.limit(1).count():
            final = components(links.unionByName(linked(rest, "links2")), folder, "c2")
    out = member.join(final, "node", "left")
    return out.select("doc_id", "n_shingles", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.coalesce("component", "node")).alias("component_id"))


def op5_fragment_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(documents(spark, sf_dir))
