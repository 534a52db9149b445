"""Repeated passages by prefix-free parsing of the corpus.

Rolling-hash triggers cut every text into phrases; a trigger depends on its own bytes
only, so equal passages are cut alike wherever they stand. A suffix that starts in a
phrase is the rest of that phrase (a suffix of a dictionary entry) followed by a suffix
of the parse. The order of suffixes is needed down to ``LENGTH`` bytes, where neighbours
that agree are repeats, and only of suffixes that can have an equal:

1. Each trigger stands for the suffixes of its phrase. Where its next ``HALF`` bytes
   are found once in the corpus (a rolling hash; a false hit costs work, not results),
   none of them has an equal. Where the whole stretch (phrase and all it takes to the
   right) is found twice, by 128-bit numbers, all of them have.
2. The stretches left over go, as bytes, to shards by what follows their trigger, so
   suffixes that are equal meet. A shard sorts the suffixes of its dictionary of phrases
   (a suffix array by doubling) and the suffixes of the parse that follow the phrases,
   with the common prefixes of neighbours, and combines both into the order of all its
   suffixes. Equality is by bytes.
3. A trigger with more than ``HOT`` occurrences would bring one shard without bound; its
   suffixes are counted by 128-bit numbers in shards of their own, each once a pack.

Gaps without a trigger use denser ones, then every position, again by their own bytes.

Every question "how often is this number found" goes to a shard of the numbers. A pack
asks once for a number, with its own count, so a number that a third of all texts share
brings its shard one entry a pack. Texts are written once in packs of
``PACK`` bytes, and a place is a pack and an offset in it.

Defined cases: null texts are empty; texts under ``LENGTH`` bytes lose nothing; repeated
rows are separate texts that repeat each other; null ids are kept; other columns are not
read by the query. One very long text is a pack of its own and takes some thirty times its
bytes of one task's memory.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm.common import documents, scratch, shards, slices, tidy, written

LENGTH, HALF, TRIGGER = 200, 100, 16
#: A trigger comes once in so many bytes; denser ones fill the gaps between them.
SPARSE, DENSE = 48, 16
PACK = 8 << 20
_B = 0xD6E8FEB86659FD93
_ASK = "shard int, pack long, kind int, keys binary, offs binary, counts binary, known binary"
#: Kinds of questions and answers: a trigger's right side, its whole stretch, one suffix,
#: runs of suffixes that are settled, and stretches that a shard puts in order.
RIGHT, WHOLE, SUFFIX, RUN, STRETCH = 0, 1, 2, 3, 4
#: Occurrences of a trigger and its right side up to which its stretches are ordered in one shard.
HOT = 4096


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(base: int, n: int) -> np.ndarray:
    out = np.ones(n, np.uint64)
    done, step = 1, np.uint64(base)
    while done < n:  # doubling: out[done:2 done] = out[:done] * base**done
        take = min(done, n - done)
        out[done : done + take] = out[:take] * step
        step = step * step
        done += take
    return out


class Rolling:
    """Hashes of any stretch of a buffer, by prefix sums of a polynomial modulo 2**64."""

    def __init__(self):
        self.up = self.down = np.zeros(0, np.uint64)
        self.letters = _mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(_B))

    def load(self, raw: np.ndarray) -> None:
        n = len(raw) + 1
        with np.errstate(over="ignore"):
            if len(self.up) < n:
                self.up, self.down = _powers(_B, n), _powers(pow(_B, -1, 1 << 64), n)
            self.sums = np.zeros(n, np.uint64)
            np.cumsum(self.letters[raw] * self.up[: n - 1], out=self.sums[1:])

    def at(self, start: np.ndarray, length) -> np.ndarray:
        return (self.sums[start + length] - self.sums[start]) * self.down[start]

    def everywhere(self, length: int) -> np.ndarray:
        n = len(self.sums) - length
        return (self.sums[length:] - self.sums[:n]) * self.down[:n] if n > 0 else np.zeros(0, np.uint64)


def phrases(roll: Rolling, starts: np.ndarray, ends: np.ndarray, length: int = LENGTH, half: int = HALF):
    """(trigger, first suffix, last suffix, level): each suffix of ``length`` is in one phrase."""
    t = _mix(roll.everywhere(TRIGGER)) >> np.uint64(32)
    sparse = np.flatnonzero((t * np.uint64(SPARSE)) >> np.uint64(32) == 0)
    long = ends - starts >= length
    s, e = starts[long], ends[long]
    if not len(s):
        z = np.zeros(0, np.int64)
        return z, z, z, z
    doc = np.searchsorted(s, sparse, "right") - 1
    ok = doc >= 0
    ok[ok] = sparse[ok] + half <= e[doc[ok]]
    m, doc = sparse[ok], doc[ok]
    before = np.r_[-1, m[:-1]]
    lo = np.maximum(np.maximum(before + 1, m - half), s[doc])
    hi = np.minimum(m, e[doc] - length)
    keep = lo <= hi
    m, lo, hi = m[keep], lo[keep], hi[keep]
    edge = np.zeros(len(roll.sums) + 1, np.int8)
    edge[s] += 1
    np.subtract.at(edge, e - length + 1, 1)
    mine = np.cumsum(edge, dtype=np.int8)
    edge[:] = 0
    edge[lo] += 1
    np.subtract.at(edge, hi + 1, 1)
    free = np.flatnonzero((mine > 0) & (np.cumsum(edge, dtype=np.int8) == 0))
    parts = [(m, lo, hi, np.zeros(len(m), np.int64))]
    if len(free):
        dense = np.flatnonzero((t * np.uint64(DENSE)) >> np.uint64(32) == 1)
        at = np.searchsorted(dense, free)
        next_ = np.where(at < len(dense), dense[np.minimum(at, max(0, len(dense) - 1))] if len(dense) else -1, 1 << 60)
        if not len(dense):
            next_ = np.full(len(free), 1 << 60)
        near = next_ - free <= half
        p, q = free[near], next_[near]
        if len(p):
            first = np.flatnonzero(np.r_[True, (q[1:] != q[:-1]) | (p[1:] != p[:-1] + 1)])
            last = np.r_[first[1:], len(p)] - 1
            parts.append((q[first], p[first], p[last], np.ones(len(first), np.int64)))
        rest = free[~near]
        parts.append((rest, rest, rest, np.full(len(rest), 2, np.int64)))
    return tuple(np.concatenate(x) for x in zip(*parts))


def spread(pack: int, n_shards: int) -> int:
    """A shard for what only passes through; a pack's number holds its partition above bit 24."""
    return ((pack >> 24) * 31 + pack) % n_shards


def _digests(pieces) -> np.ndarray:
    """128-bit numbers of byte strings, as rows of two halves."""
    raw = b"".join(map(xxhash.xxh3_128_digest, pieces))
    return np.frombuffer(raw, np.uint64).reshape(-1, 2)


def _alike(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first place of each distinct row of numbers, the row that each place has), in order."""
    order = np.lexsort(keys.T[::-1])
    some = keys[order]
    new = np.r_[True, (some[1:] != some[:-1]).any(axis=1)] if len(keys) else np.zeros(0, bool)
    at = np.empty(len(keys), np.int64)
    at[order] = np.cumsum(new) - 1
    return order[new], at


def _asks(pack: int, kind: int, keys: np.ndarray, offs: np.ndarray, n_shards: int):
    """Ask rows of one pack: each number (a row of keys) once, with the place that carries its answer.

    Of suffixes, those that the pack itself has twice are known here; a place below 0 only
    lends its number and wants no answer.
    """
    if not len(keys):
        return
    first, at = _alike(keys)
    times = np.bincount(at, minlength=len(first))
    values, place = keys[first], offs[first].astype(np.int32)
    if kind == SUFFIX:
        known = offs[(times[at] > 1) & (offs >= 0)]
        if len(known):
            yield spread(pack, n_shards), pack, kind, b"", b"", b"", np.sort(known).astype(np.int32).tobytes()
        place[times > 1] = -1
    shard = (values[:, 0] >> np.uint64(8)) % np.uint64(n_shards)
    order = np.argsort(shard, kind="stable")
    times = times.astype(np.int32)
    cuts = np.flatnonzero(np.r_[True, shard[order][1:] != shard[order][:-1]])
    for a, b in zip(cuts, np.r_[cuts[1:], len(order)]):
        some = order[a:b]
        yield int(shard[some[0]]), pack, kind, values[some].tobytes(), place[some].tobytes(), times[some].tobytes(), b""


def _stretch_rows(pack: int, right: np.ndarray, facts: np.ndarray, pieces: list[bytes], n_shards: int):
    """Stretches of one pack for their shards. ``facts``: place of the first suffix, bytes from
    it to the trigger, suffixes less one, whether it only lends; one row a stretch."""
    shard = ((right >> np.uint64(8)) % np.uint64(n_shards)).astype(np.int64)
    order = np.argsort(shard, kind="stable")
    cuts = np.flatnonzero(np.r_[True, shard[order][1:] != shard[order][:-1]]) if len(order) else []
    for a, b in zip(cuts, [*cuts[1:], len(order)]):
        some = order[a:b]
        yield int(shard[some[0]]), pack, STRETCH, b"".join(pieces[i] for i in some), facts[some].astype(np.int32).tobytes(), b"", b""


def _batch(rows: list) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary()]
    columns = list(zip(*rows)) or [()] * 7
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=["shard", "pack", "kind", "keys", "offs", "counts", "known"])


def _padded(strings: list[bytes], width: int) -> np.ndarray:
    return np.frombuffer(b"".join(x.ljust(width, b"\0") for x in strings), np.uint8).reshape(-1, width)


def dictionary_ranks(phrases_: list[bytes]) -> np.ndarray:
    """Rank of the suffix of each phrase at each place among the suffixes of all phrases.

    Suffixes end with their phrase; equal ones have one rank. By doubling: ranks of eight
    bytes, then of sixteen, until the longest phrase is covered.
    """
    longest = max(map(len, phrases_), default=0)
    width = -(-max(longest, 1) // 8) * 8
    text = np.zeros((len(phrases_), width + 8), np.int64)
    text[:, :width] = _padded(phrases_, width)
    size = np.array(list(map(len, phrases_)), np.int64)
    text[:, :width] += np.arange(width) < size[:, None]  # what ends is less than a byte of 0
    word = np.zeros((len(phrases_), width + 1), np.int64)
    for i in range(6):  # nine bits a place; the last column is past every end, its rank is 1
        word = word << 9 | text[:, i : i + width + 1]
    rank = np.unique(word, return_inverse=True)[1].reshape(word.shape).astype(np.int64) + 1
    covered = 6
    while covered < longest:
        ahead = np.ones_like(rank)
        ahead[:, : max(0, width + 1 - covered)] = rank[:, covered:]
        rank = np.unique(rank * (int(rank.max(initial=0)) + 1) + ahead, return_inverse=True)[1].reshape(word.shape).astype(np.int64) + 1
        covered *= 2
    return rank


def parse_order(contexts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(rank of each text that follows a phrase, common prefix of each rank with the one before)."""
    distinct = sorted(set(contexts))
    place = {x: i for i, x in enumerate(distinct)}
    ranks = np.fromiter((place[x] for x in contexts), np.int64, len(contexts))
    size = np.array(list(map(len, distinct)), np.int64)
    table = _padded(distinct, max(1, int(size.max(initial=1))))
    same = table[1:] == table[:-1]
    prefix = np.where(same.all(axis=1), table.shape[1], same.argmin(axis=1))
    return ranks, np.r_[0, np.minimum(prefix, np.minimum(size[1:], size[:-1]))].astype(np.int64)


def corpus_order(stretches: list[bytes], before: np.ndarray, last: np.ndarray, length: int = LENGTH):
    """(stretch, place in it, equal) of all suffixes of the stretches in their order.

    ``before``: bytes from a stretch's start to its trigger; ``last``: place of its last
    suffix. ``equal`` says that a suffix agrees with the one before it on ``length`` bytes:
    the rest of the phrase is the same suffix of the dictionary, and what follows agrees
    on the bytes that are left.
    """
    phrase = [x[: a + TRIGGER] for x, a in zip(stretches, before.tolist())]
    number = {x: i for i, x in enumerate(dict.fromkeys(phrase))}
    which = np.fromiter((number[x] for x in phrase), np.int64, len(phrase))
    of_dictionary = dictionary_ranks(list(number))
    of_parse, prefix = parse_order([x[a + TRIGGER :] for x, a in zip(stretches, before.tolist())])
    owner = np.repeat(np.arange(len(stretches)), last + 1)
    place = _each(np.zeros(len(last), np.int64), last)
    first, second = of_dictionary[which[owner], place], of_parse[owner]
    order = np.lexsort((second, first))
    owner, place, first, second = owner[order], place[order], first[order], second[order]
    need = length - TRIGGER - before[owner] + place  # bytes of the parse that a suffix takes
    # agreeing on n bytes: no neighbour between two ranks has a shorter common prefix
    equal = np.zeros(len(order), bool)
    near = 1 + np.flatnonzero(first[1:] == first[:-1])
    near = near[np.argsort(need[near], kind="stable")]
    cuts = np.flatnonzero(np.r_[True, need[near][1:] != need[near][:-1]]) if len(near) else []
    for a, b in zip(cuts, [*cuts[1:], len(near)]):
        some = near[a:b]
        breaks = np.cumsum(prefix < need[some[0]])
        equal[some] = breaks[second[some - 1]] == breaks[second[some]]
    return owner, place, equal


def _ordered(t: pa.Table) -> list[tuple]:
    """Answer rows for a shard's stretches: by pack, the places of suffixes that have an equal."""
    packs, facts, pieces = [], [], []
    for pack, raw, some in zip(*(t.column(c).to_pylist() for c in ("pack", "keys", "offs"))):
        f = np.frombuffer(some, np.int32).reshape(-1, 4).astype(np.int64)
        ends = np.cumsum(f[:, 2] + LENGTH)
        pieces += [raw[a:b] for a, b in zip(np.r_[0, ends[:-1]].tolist(), ends.tolist())]
        facts.append(f)
        packs += [pack] * len(f)
    if not pieces:
        return []
    facts, packs = np.concatenate(facts), np.array(packs, np.int64)
    owner, place, equal = corpus_order(pieces, facts[:, 1], facts[:, 2])
    many = equal | np.r_[equal[1:], False]
    hit = many & (facts[owner, 3] == 0)
    owner, place = owner[hit], place[hit]
    order = np.argsort(packs[owner], kind="stable")
    owner, place = owner[order], place[order]
    cuts = np.flatnonzero(np.r_[True, packs[owner][1:] != packs[owner][:-1]]) if len(owner) else []
    return [(int(packs[owner[a]]), SUFFIX, (facts[owner[a:b], 0] + place[a:b]).astype(np.int32).tobytes(), b"") for a, b in zip(cuts, [*cuts[1:], len(owner)])]


def _answers(asks: DataFrame) -> DataFrame:
    """pack, kind, offs, counts of all places whose number is found twice or more.

    The count is below 0 at one of the places, which speaks for all.
    """

    def answer(key, t):
        rows = [(p, k, x, b"") for p, k, x in zip(t.column("pack").to_pylist(), t.column("kind").to_pylist(), t.column("known").to_pylist()) if x]
        kinds = t.column("kind").to_numpy()
        for kind in np.unique(kinds):
            some = t.filter(pa.array(kinds == kind)).sort_by("pack")
            if kind == STRETCH:
                rows += _ordered(some)
                continue
            packs = some.column("pack").to_numpy()
            width = 1 if kind == RIGHT else 2
            keys, offs, n = ([np.frombuffer(x.as_py(), d) for x in some.column(c)] for c, d in (("keys", np.uint64), ("offs", np.int32), ("counts", np.int32)))
            owner = np.repeat(np.arange(len(packs)), [len(x) for x in offs])
            if not len(owner):
                continue
            keys, offs, n = np.concatenate(keys).reshape(-1, width), np.concatenate(offs), np.concatenate(n)
            first, at = _alike(keys)
            many = np.minimum(np.bincount(at, n), 2**31 - 1).astype(np.int32)[at]
            many[first] *= -1
            hit = (np.abs(many) > 1) & (offs >= 0)
            owner, offs, many = owner[hit], offs[hit], many[hit]
            cuts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]]) if len(owner) else np.zeros(0, int)
            rows += [(int(packs[owner[a]]), int(kind), offs[a:b].tobytes(), many[a:b].tobytes()) for a, b in zip(cuts, np.r_[cuts[1:], len(owner)].astype(int))]
        columns = list(zip(*rows)) or [()] * 4
        return pa.table({"pack": pa.array(columns[0], pa.int64()), "kind": pa.array(columns[1], pa.int32()), "offs": pa.array(columns[2], pa.binary()), "counts": pa.array(columns[3], pa.binary())})

    return asks.groupBy("shard").applyInArrow(answer, "pack long, kind int, offs binary, counts binary")


def packed(df: DataFrame, id_col: str, text_col: str, pack_bytes: int = PACK) -> DataFrame:
    """pack, start, id, text: each text's place in the packed corpus."""

    def step(batches):
        pack, at = TaskContext.get().partitionId() << 24, 0
        for batch in batches:
            sizes = [len(t.as_buffer()) if t.is_valid else 0 for t in batch.column(1)]
            packs, starts = [], []
            for n in sizes:
                if at and at + n > pack_bytes:
                    pack, at = pack + 1, 0
                packs.append(pack)
                starts.append(at)
                at += n
            yield pa.RecordBatch.from_arrays([pa.array(packs, pa.int64()), pa.array(starts, pa.int64()), batch.column(0), batch.column(1)], names=["pack", "start", "_id", "_text"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text")).mapInArrow(step, f"pack long, start long, _id {kind}, _text string")


def _loaded(roll: Rolling, texts: list[bytes], starts: np.ndarray):
    """Runs of texts of one pack, loaded one after another: their places in the buffer and the pack."""
    for a, b in slices(texts):
        raw = np.frombuffer(b"".join(texts[a:b]), np.uint8)
        size = np.array([len(x) for x in texts[a:b]], np.int64)
        ends = np.cumsum(size)
        if len(raw) < LENGTH:
            continue
        roll.load(raw)
        yield ends - size, ends, int(starts[a]), raw.tobytes()


def _keys(roll: Rolling, raw: bytes, m, lo, hi, level) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of each trigger's right side, and of its stretch with the places in it."""
    right = _mix(roll.at(m, HALF) + level.astype(np.uint64))
    head = (((hi - lo) * 512 + (m - lo)) * 4 + level).astype(np.uint32).tobytes()
    whole = _digests([head[4 * i : 4 * i + 4] + raw[a : b + LENGTH] for i, (a, b) in enumerate(zip(lo.tolist(), hi.tolist()))])
    return right[:, None], whole


def _first_asks(packs: DataFrame, n_shards: int) -> DataFrame:
    def step(batches):
        roll, now, right, whole, offs = Rolling(), None, [], [], []

        def flush():
            if right:
                o = np.concatenate(offs)
                rows = [*_asks(now, RIGHT, np.concatenate(right), o, n_shards), *_asks(now, WHOLE, np.concatenate(whole), o, n_shards)]
                right.clear(), whole.clear(), offs.clear()
                yield _batch(rows)

        for batch in batches:
            names = batch.column(0).to_numpy()
            cuts = np.flatnonzero(np.r_[True, names[1:] != names[:-1]])
            for a, b in zip(cuts, np.r_[cuts[1:], len(names)]):
                if now is not None and names[a] != now:
                    yield from flush()
                now = int(names[a])
                texts = [t.as_buffer().to_pybytes() for t in batch.column(2)[a:b]]
                for starts, ends, base, raw in _loaded(roll, texts, batch.column(1)[a:b].to_numpy()):
                    m, lo, hi, level = phrases(roll, starts, ends)
                    r, w = _keys(roll, raw, m, lo, hi, level)
                    right.append(r)
                    whole.append(w)
                    offs.append(lo + base)
        yield from flush()

    return packs.select("pack", "start", "_text").mapInArrow(step, _ASK)


def _texts(docs: pa.Table) -> tuple[list[bytes], np.ndarray]:
    return [t.as_buffer().to_pybytes() if t.is_valid else b"" for t in docs.column("_text")], docs.column("start").to_numpy()


def _sets(answers: pa.Table) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Places and counts by kind."""
    out = {}
    kinds = answers.column("kind").to_numpy()
    for kind in np.unique(kinds):
        some = answers.filter(pa.array(kinds == kind))
        out[int(kind)] = tuple(np.concatenate([np.frombuffer(x.as_py(), np.int32) for x in some.column(c)]).astype(np.int64) for c in ("offs", "counts"))
    return out


def _counted(keys: np.ndarray, places: np.ndarray, answer) -> tuple[np.ndarray, np.ndarray]:
    """(count of each key in the corpus, whether the place speaks for its key); 1 if unanswered."""
    count, speaks = np.ones(len(keys), np.int64), np.zeros(len(keys), bool)
    if answer is not None and len(answer[0]):
        carrier = np.searchsorted(places, answer[0])
        first, at = _alike(keys)
        of_key = np.ones(len(first), np.int64)
        of_key[at[carrier]] = np.abs(answer[1])
        count = of_key[at]
        speaks[carrier[answer[1] < 0]] = True
    return count, speaks


def _each(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    n = hi - lo + 1
    return np.repeat(lo - np.r_[0, np.cumsum(n)[:-1]].astype(np.int64), n) + np.arange(n.sum()) if len(n) else np.zeros(0, np.int64)


def _second_asks(packs: DataFrame, answers: DataFrame, n_shards: int, hot: int = HOT) -> DataFrame:
    def step(key, docs, got):
        pack, rows = key[0].as_py(), []
        sets = _sets(got)
        docs = docs.sort_by("start")
        texts, places = _texts(docs)
        roll = Rolling()
        found = []
        for starts, ends, base, raw in _loaded(roll, texts, places) if sets else ():
            m, lo, hi, level = phrases(roll, starts, ends)
            found.append((m + base, lo + base, hi + base, *_keys(roll, raw, m, lo, hi, level)))
        if found:
            m, lo, hi, right, whole = (np.concatenate(x) for x in zip(*found))
            order = np.argsort(lo, kind="stable")  # no two phrases share a suffix
            m, lo, hi, right, whole = (x[order] for x in (m, lo, hi, right, whole))
            n_right, _ = _counted(right, lo, sets.get(RIGHT))
            n_whole, speaks = _counted(whole, lo, sets.get(WHOLE))
            settled = n_whole > 1
            part = (n_right > 1) & ~settled
            # others share the right side but not the stretch: one of its places lends its suffixes
            lends = settled & speaks & (n_right > n_whole)
            often = n_right > hot
            keys, offs, pieces = [], [], []
            cold = np.flatnonzero((part | lends) & ~often)
            facts = np.column_stack([lo, m - lo, hi - lo, lends])[cold]
            joined = b"".join(texts)  # a place is an offset in the pack
            for a, b in zip(lo[cold].tolist(), hi[cold].tolist()):
                pieces.append(joined[a : b + LENGTH])
            rows += _stretch_rows(pack, right[cold, 0], facts, pieces, n_shards)
            for chosen, sign in ((part & often, 1), (lends & often, 0)):
                p = _each(lo[chosen], hi[chosen])
                keys.append(_digests([joined[a : a + LENGTH] for a in p.tolist()]))
                offs.append(p if sign else np.full(len(p), -1))
            rows += _asks(pack, SUFFIX, np.concatenate(keys), np.concatenate(offs), n_shards)
            runs = np.stack([lo[settled], hi[settled]], 1).astype(np.int32)
            if len(runs):
                rows.append((spread(pack, n_shards), pack, RUN, b"", b"", b"", runs.tobytes()))
        return pa.Table.from_batches([_batch(rows)])

    return packs.select("pack", "start", "_text").groupBy("pack").cogroup(answers.groupBy("pack")).applyInArrow(step, _ASK)


def spans_of(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", whole_characters: bool = False, hot: int = HOT) -> DataFrame:
    """id, n_bytes, spans (start, end in bytes) that repeat, and the kept bytes of every row.

    With ``whole_characters`` a character that loses a byte is lost, so the rest is text.
    """
    spark = df.sparkSession
    folder = scratch(spark)
    n_shards = shards(df)
    packs = written(packed(df, id_col, text_col), folder, "packs")
    first = written(_answers(_first_asks(packs, n_shards)), folder, "first")
    tidy(spark)
    second = written(_answers(_second_asks(packs, first, n_shards, hot)), folder, "second")
    tidy(spark)
    kind = df.schema[id_col].dataType.simpleString()

    def step(key, docs, got):
        docs = docs.sort_by("start")
        texts, places = _texts(docs)
        total = int(places[-1]) + len(texts[-1]) if texts else 0
        edge = np.zeros(total + 1, np.int32)
        sets = _sets(got)
        if SUFFIX in sets:
            np.add.at(edge, sets[SUFFIX][0], 1)
            np.subtract.at(edge, sets[SUFFIX][0] + LENGTH, 1)
        if RUN in sets:
            runs = sets[RUN][0].reshape(-1, 2)
            np.add.at(edge, runs[:, 0], 1)
            np.subtract.at(edge, runs[:, 1] + LENGTH, 1)
        hit = np.cumsum(edge, dtype=np.int32, out=edge)[:-1] > 0
        spans, kept = [], []
        for text, at in zip(texts, places):
            mask = hit[at : at + len(text)]
            if not mask.any():
                spans.append([])
                kept.append(text)
                continue
            if whole_characters:
                char = np.cumsum((np.frombuffer(text, np.uint8) & 0xC0) != 0x80) - 1
                mask = np.bincount(char, mask)[char] > 0
            turn = np.flatnonzero(np.diff(np.r_[False, mask, False].astype(np.int8)))
            spans.append([{"start": int(a), "end": int(b)} for a, b in turn.reshape(-1, 2)])
            kept.append(np.frombuffer(text, np.uint8)[~mask].tobytes())
        pair = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        return pa.table({"_id": docs.column("_id"), "n_bytes": pa.array([len(t) for t in texts], pa.int64()), "spans": pa.array(spans, pair), "kept": pa.array(kept, pa.binary())})

    got = packs.groupBy("pack").cogroup(second.groupBy("pack")).applyInArrow(step, f"_id {kind}, n_bytes long, spans array<struct<start: long, end: long>>, kept binary")
    return got.withColumnRenamed("_id", id_col)


def cleaned(df: DataFrame, text_col: str = "text") -> DataFrame:
    """df with its repeated passages cut out of the text; null texts become empty."""
    row = F.struct(*[F.col(c) for c in df.columns if c != text_col])
    got = spans_of(df.select(row.alias("_row"), text_col), "_row", text_col, whole_characters=True)
    return got.select("_row.*", F.col("kept").cast("string").alias(text_col)).select(*df.columns)


def op8_prefix_free_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = spans_of(documents(spark, sf_dir))
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["start"])
    return got.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
