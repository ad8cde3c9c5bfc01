"""Jaccard join of 5-word shingle sets through groups and a token-group matrix.

1. Each text becomes a set of 64-bit shingle hashes; equal sets form a class.
2. Classes are partitioned into groups of similar ones: those that share one of four
   min-hashes are compared with the bucket's centre, and exact links to centres are united.
   A group is connected by such links, so no pair inside it needs to be looked at again.
   Classes that are still alone are then linked with a few of those next to them in the
   rows of the matrix that comes next, which makes groups of loose clusters too.
3. The matrix of tokens and groups holds, for each group, the union of its members' prefix
   tokens: the first quarter of a set (and one more) in an order that puts frequent tokens
   last. Sets that link share a token of both prefixes, so only groups that share a matrix
   row can hold a link. A row also has the place of the token in its set: what lies behind
   the first common token bounds the overlap, and a row counts only if that bound reaches
   what a link needs at the two sizes. (A later row could not count if the first doesn't.)
4. Only pairs of groups that the bound lets pass are opened, and the sets in them compared
   exactly on the texts. Components of all links give the classes of near duplicates.

Tokens are counted over all sets, and those that most sets hold, at most HEAVY of them, give
the order; any order gives the same links, so the bound costs time and no link.

Null, empty or blank text: no shingles, linked with nothing. Repeated rows are one class.
Rows whose id is null belong to their component like all others, but don't name it.
Extra columns are not read, but pass through keep_representatives.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.broadcast import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textscan as ts
from .components import components
from .fingerprints import pack_text, unpack_text
from .keyfilter import key_filter, passes
from .storage import discard, saved

WORDS, PERCENT = 5, 75
CENTRES, LOW = 4, 12
#: What class ids are combined with, so that each min-hash orders centres anew.
TURNS = (0, 0x4000000000000000, -0x7FFFFFFFFFFFFFFF - 1, -0x4000000000000000)
HEAVY, HEAVY_LEAST = 4_000_000, 2
#: A pair goes to its centre for comparison if the smallest LOW tokens agree this much.
HOPEFUL = 0.4
SLICE = 400
#: Single classes are chained by their first FIRST tokens and one of CHAINED others (a power of two), to
#: STEPS of those next to them each way.
FIRST, CHAINED, STEPS = 8, 4, 8
#: Members of either group that are tried before they are opened, about.
FEW = 4
#: Size of the filter of tokens that two sets hold, as a power of two bits (16 MB).
SHARED_BITS = 27
#: Buckets of the parities that matrix rows carry.
SHORT = 512
#: Sets whose buckets are counted at a time: 2 MB.
COUNTED = 512
#: Classes that a task remembers having met.
REMEMBERED = 200_000
PIECE = 20_000
#: Matrix rows that are looked at together, unless one token has more: 13 MB, of which a few copies are made.
ROWS = 125_000
#: Pairs that are made distinct before they are handed on, about.
PAIRS = 500_000
#: Tokens that are counted together before their repetitions are handed on: 16 MB.
TOGETHER = 2_000_000
#: Tokens of a slice of the hashes, about.
SLICE_TOKENS = 4_000_000
#: Tokens of a slice that are summed at a time, about.
SUMMED = 250_000


def shingle_sets(data: np.ndarray, offsets: np.ndarray, size: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each row of a block, one after the other, and where each row's begin."""
    words = ts.Words(data, offsets, ts.SPACED_WORD)
    hashes = words.hashes()
    starts, rows = ts.window_rows(words.first, size)
    tokens = [ts.hash_windows(hashes, size)[starts]]
    owners = [rows]
    for n in range(1, size):
        short = np.flatnonzero(words.counts == n)
        if len(short):
            tokens.append(ts.hash_windows(hashes, n)[words.first[short]])
            owners.append(short)
    tokens, owners = np.concatenate(tokens), np.concatenate(owners)
    order = np.lexsort((tokens, owners))
    tokens, owners = tokens[order], owners[order]
    new = np.ones(len(tokens), bool)
    new[1:] = (tokens[1:] != tokens[:-1]) | (owners[1:] != owners[:-1])
    tokens, owners = tokens[new], owners[new]
    return tokens, np.searchsorted(owners, np.arange(len(offsets)))


def _set_blocks(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """Blocks of rows: first, last, tokens, their places, and the class id of each row."""
    data, offsets = ts.buffers(column)
    for a, b in ts.row_blocks(offsets):
        tokens, first = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
        raw = memoryview(tokens.astype("<u8").tobytes())
        ids = np.array([xxhash.xxh3_64_intdigest(raw[8 * i : 8 * j]) if j > i else 0 for i, j in zip(first[:-1].tolist(), first[1:].tolist(), strict=True)], np.uint64)
        yield a, b, tokens, first, ids.view(np.int64)


def _lists(values: np.ndarray, counts: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(values.view(np.int64)))


def parities(tokens: np.ndarray, n: np.ndarray) -> pa.Array:
    """For each set whether an odd number of its tokens fall into each of 2 n buckets or more, as bits.

    Two sets of n and m elements differ in at least as many elements as their bits differ, so
    (n + m - differing bits) / 2 bounds what they have in common. Buckets are a power of two,
    and a longer row of bits folds to a shorter one.
    """
    bits = 1 << np.ceil(np.log2(np.maximum(2 * n, 64))).astype(np.int64)
    ends = np.cumsum(bits)
    place = np.repeat(ends - bits, n) + (tokens & np.repeat(bits - 1, n).astype(np.uint64)).astype(np.int64)
    odd = np.bincount(place, minlength=int(ends[-1]) if len(ends) else 0) & 1
    offsets = np.concatenate([[0], ends // 8]).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(np.packbits(odd.astype(np.uint8), bitorder="little").tobytes())])


def short_parities(tokens: np.ndarray, owner: np.ndarray, rows: int) -> np.ndarray:
    """The same over SHORT buckets for every set, as rows of 64-bit words. owner has to rise."""
    out = np.empty((rows, SHORT // 64), np.uint64)
    for a in range(0, rows, COUNTED):
        b = min(a + COUNTED, rows)
        i, j = np.searchsorted(owner, [a, b])
        odd = np.bincount((owner[i:j] - a) * SHORT + (tokens[i:j] & np.uint64(SHORT - 1)).astype(np.int64), minlength=(b - a) * SHORT) & 1
        out[a:b] = np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64).reshape(b - a, SHORT // 64)
    return out


def _words(column: pa.Array) -> np.ndarray:
    return ts.buffers(column)[0].view(np.uint64).reshape(-1, SHORT // 64)


def _binary(words: np.ndarray) -> pa.Array:
    offsets = np.arange(len(words) + 1, dtype=np.int32) * (SHORT // 8)
    return pa.Array.from_buffers(pa.binary(), len(words), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(words.tobytes())])


def _differing(x: bytes, y: bytes) -> int:
    """Differing bits of two rows of parities, the longer one folded."""
    if len(x) < len(y):
        x, y = y, x
    a, size = int.from_bytes(x, "little"), len(x)
    while size > len(y):
        size //= 2
        a = (a >> 8 * size) ^ (a & (1 << 8 * size) - 1)
    return (a ^ int.from_bytes(y, "little")).bit_count()


def promising(pairs: DataFrame, classes: DataFrame) -> DataFrame:
    """The pairs (a, b) of class ids that may link, by the bound that sizes and parities give."""
    side = lambda c: classes.select(F.col("cid").alias(c), F.col("n").alias("n" + c), F.col("parity").alias("p" + c))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "nb", "pa", "pb")

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.column(2).to_numpy() + batch.column(3).to_numpy()
            differing = np.array([_differing(x, y) for x, y in zip(batch.column(4).to_pylist(), batch.column(5).to_pylist(), strict=True)], np.int64)
            common = (n - differing) // 2
            yield batch.select(["a", "b"]).filter(pa.array((100 + PERCENT) * common >= PERCENT * n))

    return both.mapInArrow(scan, "a long, b long")


def signatures(docs: DataFrame, key: str, text: str) -> DataFrame:
    """key, n, cid, keys (min-hashes), low (smallest tokens), parity (see parities) of every row."""
    schema = T.StructType([T.StructField(key, docs.schema[key].dataType), T.StructField("n", T.LongType()), T.StructField("cid", T.LongType()), T.StructField("keys", T.ArrayType(T.LongType())), T.StructField("low", T.ArrayType(T.LongType())), T.StructField("parity", T.BinaryType())])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, tokens, first, ids in _set_blocks(batch.column(1)):
                n = np.diff(first)
                full = n > 0
                keys = np.zeros((int(full.sum()), CENTRES), np.uint64)
                for i in range(CENTRES):
                    if len(keys):
                        keys[:, i] = np.minimum.reduceat(ts.mix(tokens ^ np.uint64(i * 0x5851F42D4C957F2D & (1 << 64) - 1)), first[:-1][full])
                lowest = np.minimum(n, LOW)
                low = tokens[np.repeat(first[:-1], lowest) + ts.ragged(lowest)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(n), pa.array(ids), _lists(keys.ravel(), full * CENTRES), _lists(low, lowest), parities(tokens, n)], names=schema.names)

    return docs.select(key, text).mapInArrow(scan, schema)


def _once(ids: np.ndarray, n: np.ndarray, seen: set[int]) -> np.ndarray:
    """Rows whose class this task hasn't met lately; what is remembered is bounded, so classes may come again."""
    rows = []
    for i in np.flatnonzero(n > 0):
        if (c := int(ids[i])) not in seen:
            if len(seen) >= REMEMBERED:
                seen.clear()
            seen.add(c)
            rows.append(i)
    return np.array(rows, np.int64)


def token_totals(docs: DataFrame, text: str, total: int) -> DataFrame:
    """(token, n) of the tokens that two sets hold at least.

    Tokens travel as sorted arrays, one for each slice of the hashes, and slices are summed in
    numpy: a row of each token in each task would cost several times the space and time. The
    number of slices follows the total, so that a slice's arrays stay small at any size. Each
    slice is a batch of its own and is summed in parts, so that neither a worker nor the JVM
    that reads from it holds copies of all of them.
    """
    bits = max(4, int(np.ceil(np.log2(max(1, total) / SLICE_TOKENS))))

    def sliced(values: np.ndarray) -> Iterator[pa.RecordBatch]:
        values.sort()
        edges = np.searchsorted(values, np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits))
        edges = np.concatenate([[0], edges, [len(values)]])
        for i in np.flatnonzero(np.diff(edges)).tolist():
            part = values[edges[i] : edges[i + 1]]
            first = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]]))
            counts = np.diff(first, append=len(part)).astype(np.uint32)
            yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([part[first].tobytes()], pa.binary()), pa.array([counts.tobytes()], pa.binary())], names=["slice", "tokens", "counts"])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        held, size = np.empty(TOGETHER, np.uint64), 0
        for batch in batches:
            for _, _, tokens, first, ids in _set_blocks(batch.column(0)):
                n = np.diff(first)
                rows = _once(ids, n, seen)
                mine = tokens[np.repeat(first[:-1][rows], n[rows]) + ts.ragged(n[rows])]
                if size + len(mine) > TOGETHER:
                    yield from sliced(held[:size])
                    size = 0
                if len(mine) > TOGETHER:
                    yield from sliced(mine)
                    continue
                held[size : size + len(mine)] = mine
                size += len(mine)
        yield from sliced(held[:size])

    def summed(held: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        low, high = min(int(t[0]) for t, _ in held), max(int(t[-1]) for t, _ in held)
        parts = -(-sum(len(t) for t, _ in held) // SUMMED)
        cuts = np.array([low + (high - low) * i // parts for i in range(1, parts)], np.uint64)
        edges = [[0, *np.searchsorted(t, cuts).tolist(), len(t)] for t, _ in held]
        for p in range(parts):
            spans = [slice(e[p], e[p + 1]) for e in edges]
            values = np.concatenate([t[s] for (t, _), s in zip(held, spans, strict=True)])
            if not len(values):
                continue
            counts = np.concatenate([c[s] for (_, c), s in zip(held, spans, strict=True)]).astype(np.int64)
            order = np.argsort(values, kind="stable")
            values, counts = values[order], counts[order]
            first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]]))
            counts = np.add.reduceat(counts, first)
            keep = counts > 1
            yield pa.RecordBatch.from_arrays([pa.array(values[first][keep].view(np.int64)), pa.array(counts[keep])], names=["token", "n"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = -1, []
        for batch in batches:
            for s, t, c in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                if s != now and held:
                    yield from summed(held)
                    held = []
                now = s
                held.append((np.frombuffer(t, np.uint64), np.frombuffer(c, np.uint32)))
        if held:
            yield from summed(held)
            held = []
        ts.release()

    sent = docs.select(text).mapInArrow(scan, "slice long, tokens binary, counts binary")
    return sent.repartition("slice").sortWithinPartitions("slice").mapInArrow(merge, "token long, n long")


def frequent_tokens(docs: DataFrame, text: str, total: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted tokens that most sets hold, no more than HEAVY of them, a rank of their frequency, and
    a filter of fixed size of all tokens that two sets hold at least."""
    totals = saved(token_totals(docs, text, total), "token-totals")
    rank = F.floor(F.log2("n")).cast("int")
    held, least = 0, 64
    for r in totals.groupBy(rank.alias("r")).agg(F.count("*").alias("m")).orderBy(F.col("r").desc()).collect():  # at most 64 rows
        held += r["m"]
        if held > HEAVY:
            break
        least = r["r"]
    found = totals.filter((rank >= least) & (F.col("n") >= HEAVY_LEAST)).select("token", rank.alias("r")).toArrow()
    shared = key_filter(totals, "token", SHARED_BITS).value
    discard(totals)
    tokens = found.column("token").to_numpy().view(np.uint64)
    order = np.argsort(tokens)
    return tokens[order], (1 + found.column("r").to_numpy()[order]).astype(np.uint8), shared


def _least_common(n: np.ndarray) -> np.ndarray:
    """The elements that a set of n shares at least with any set it links to."""
    return (PERCENT * n + 99) // 100


def prefixes(docs: DataFrame, text: str, heavy: Broadcast) -> DataFrame:
    """cid, n, tokens, places, parity: size and prefix of every class (at least once), with the tokens' places in
    the order; tokens that no other set holds can't be shared and are left out."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, rank, shared = heavy.value
        seen: set[int] = set()
        for batch in batches:
            for _, _, tokens, first, ids in _set_blocks(batch.column(0)):
                n = np.diff(first)
                rows = _once(ids, n, seen)
                if not len(rows):
                    continue
                n = n[rows]
                mine = tokens[np.repeat(first[:-1][rows], n) + ts.ragged(n)]
                owner = np.repeat(np.arange(len(rows)), n)
                if len(known):
                    at = np.minimum(np.searchsorted(known, mine), len(known) - 1)
                    late = np.where(known[at] == mine, rank[at], 0).astype(np.int64)
                    mine = mine[np.argsort(owner << 8 | late, kind="stable")]
                place = ts.ragged(n)
                keep = (place <= (n - _least_common(n))[owner]) & passes(shared, mine)
                size = np.bincount(owner[keep], minlength=len(n))
                some = size > 0
                yield pa.RecordBatch.from_arrays([pa.array(ids[rows][some]), pa.array(n[some]), _lists(mine[keep], size[some]), _lists(place[keep], size[some]), _binary(short_parities(mine, owner, len(n))[some])], names=["cid", "n", "tokens", "places", "parity"])

    return docs.select(text).mapInArrow(scan, "cid long, n long, tokens array<long>, places array<long>, parity binary")


def grouped_prefixes(docs: DataFrame, text: str, heavy: Broadcast, grouped: DataFrame) -> DataFrame:
    """cid, g, many, n, tokens, places, parity: prefixes with their group, and whether it has other members."""
    return in_groups(prefixes(docs, text, heavy), grouped)


def in_groups(prefix: DataFrame, grouped: DataFrame) -> DataFrame:
    joined = prefix.join(grouped.withColumnRenamed("node", "cid"), "cid", "left")
    return joined.select("cid", F.coalesce("label", "cid").alias("g"), F.col("label").isNotNull().alias("many"), "n", "tokens", "places", "parity")


def _overlap_left(n: np.ndarray, place: np.ndarray) -> np.ndarray:
    """100 + PERCENT times the sizes that a partner may have at most, if the first common token is at that place.

    Sets of n and m elements link if (100 + PERCENT) * common >= PERCENT * (n + m), and no more
    than n - place elements are left to be common.
    """
    return (100 + PERCENT) * (n - place) - PERCENT * n


#: Columns of matrix rows: owner (a group or a class) and its side; rows of one side needn't meet.
ROW = ("token", "owner", "side", "n", "room", "many", "parity")


def matrix(prefix: DataFrame, owner: str, side: str, many: Column) -> DataFrame:
    """ROW columns: a group's row of a token has the smallest size of the sets that bear it, and the
    largest partner (times PERCENT) that their places leave room for. many: the owner is a group of
    several classes, so that its size and parity say nothing of each."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(4)
            sizes = np.diff(lists.offsets.to_numpy())
            owner, side, many, n = (np.repeat(batch.column(i).to_numpy(zero_copy_only=False), sizes) for i in range(4))
            if len(n):
                rows = _united([lists.flatten().to_numpy(), owner, side, n, _overlap_left(n, batch.column(5).flatten().to_numpy()), many, np.repeat(_words(batch.column(6)), sizes, axis=0)])
                for i in range(0, len(rows[0]), PIECE):
                    piece = [x[i : i + PIECE] for x in rows]
                    yield pa.RecordBatch.from_arrays([*(pa.array(x) for x in piece[:-1]), _binary(piece[-1])], names=ROW)

    return prefix.select(F.col(owner).alias("o"), F.col(side).alias("s"), many.alias("many"), "n", "tokens", "places", "parity").mapInArrow(scan, "token long, owner long, side long, n long, room long, many boolean, parity binary")


def _united(columns: list[np.ndarray]) -> list[np.ndarray]:
    """Matrix rows by token and owner, those of one token and owner made one."""
    order = np.lexsort((columns[1], columns[0]))
    token, owner, side, n, room, many, parity = (x[order] for x in columns)
    first = np.flatnonzero(np.concatenate([[True], (token[1:] != token[:-1]) | (owner[1:] != owner[:-1])]))
    return [token[first], owner[first], side[first], np.minimum.reduceat(n, first), np.maximum.reduceat(room, first), many[first], parity[first]]


def _largest_side(token: np.ndarray, side: np.ndarray) -> np.ndarray:
    """Which rows are on the side that has most rows of their token (the others of a tie are not)."""
    order = np.lexsort((side, token))
    t, s = token[order], side[order]
    run = np.flatnonzero(np.concatenate([[True], (t[1:] != t[:-1]) | (s[1:] != s[:-1])]))
    size = np.diff(np.append(run, len(t)))
    best = np.lexsort((-size, t[run]))
    best = best[np.concatenate([[True], t[run][best][1:] != t[run][best][:-1]])]
    top = np.zeros(len(run), bool)
    top[best] = True
    out = np.empty(len(t), bool)
    out[order] = np.repeat(top, size)
    return out


def _meeting(token: np.ndarray, side: np.ndarray, n: np.ndarray, room: np.ndarray, steps: int | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (i, j) of rows of one token and two sides whose bounds let their sets link.

    Rows lie by token and size. Each row meets the next one, then the one after it, for as long
    as the token is the same and the sizes fit, and likewise backwards; all rows take each step
    together. Rows of a token's largest side only wait to be met, so a side that bears a token
    thousands of times costs nothing within itself. steps: so many and no more each way.
    """
    begins = np.flatnonzero(~_largest_side(token, side))
    for way in (1, -1):
        i, step = begins, way
        while len(i) and (steps is None or abs(step) <= steps):
            i = i[(i + step < len(token)) & (i + step >= 0)]
            j = i + step
            fits = (PERCENT * n[j] <= room[i]) if way > 0 else (100 * n[j] >= PERCENT * n[i])
            i = i[(token[i] == token[j]) & fits]
            j = i + step
            both = (PERCENT * n[i] <= room[j]) & (PERCENT * n[j] <= room[i]) & (side[i] != side[j])
            yield i[both], j[both]
            step += way


def qualifying(rows: DataFrame, steps: int | None = None) -> DataFrame:
    """(a, b, single): owners that share a matrix row which leaves room for a link, a < b, and whether both are single classes.

    steps: only those so near in the order of the sizes that bear a token, so no more than twice as many for each row.
    """

    def pairs(token: np.ndarray, owner: np.ndarray, side: np.ndarray, n: np.ndarray, room: np.ndarray, many: np.ndarray, parity: np.ndarray) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for i, j in _meeting(token, side, n, room, steps):
            both = n[i] + n[j]
            common = (both - np.bitwise_count(parity[i] ^ parity[j]).sum(axis=1, dtype=np.int64)) // 2
            may = many[i] | many[j] | ((100 + PERCENT) * common >= PERCENT * both)
            i, j = i[may], j[may]
            held.append((np.minimum(owner[i], owner[j]), np.maximum(owner[i], owner[j]), ~(many[i] | many[j])))
            size += len(i)
            if size > PAIRS:
                yield _distinct(held)
                held, size = [], 0
        if size:
            yield _distinct(held)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        for batch in _with_end(batches):
            if batch:
                if batch.num_rows:
                    held.append((*(c.to_numpy(zero_copy_only=False) for c in batch.columns[:-1]), _words(batch.column(6))))
                if not held or held[0][0][0] == held[-1][0][-1] or sum(len(h[0]) for h in held) < ROWS:
                    continue
            if not held:
                continue
            columns = _united([np.concatenate(x) for x in zip(*held, strict=True)])
            token, n = columns[0], columns[3]
            done = int(np.searchsorted(token, token[-1])) if batch else len(token)
            held = [tuple(c[done:] for c in columns)]
            tie = ts.mix((columns[1] ^ token)[:done].view(np.uint64)) if steps else token[:done]  # equal sizes: other neighbours for each token
            order = np.lexsort((tie, n[:done], token[:done]))
            yield from pairs(*(c[:done][order] for c in columns))

    dealt = rows.repartition("token").sortWithinPartitions("token")
    return dealt.mapInArrow(scan, "a long, b long, single boolean").groupBy("a", "b").agg(F.first("single").alias("single"))


def _with_end(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch | None]:
    yield from batches
    yield None


def _distinct(held: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    a, b, single = (np.concatenate(x) for x in zip(*held, strict=True))
    order = np.lexsort((b, a))
    a, b, single = a[order], b[order], single[order]
    first = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])) if len(a) else np.zeros(0, np.int64)
    return pa.RecordBatch.from_arrays([pa.array(a[first]), pa.array(b[first]), pa.array(single[first])], names=["a", "b", "single"])


def class_texts(docs: DataFrame, text: str, wanted: DataFrame) -> DataFrame:
    """(cid, body): one packed text of each wanted class (and of a few others that pass the filter)."""
    wanted = key_filter(wanted, "c")

    def bodies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for a, b, _, first, ids in _set_blocks(batch.column(0)):
                may = passes(wanted.value, ids)
                rows = _once(ids, np.diff(first) * may, seen)
                texts = batch.column(0).slice(a, b - a).take(pa.array(rows)).to_pylist()
                yield pa.RecordBatch.from_arrays([pa.array(ids[rows]), pa.array([pack_text(t) for t in texts], pa.binary())], names=["cid", "body"])

    return saved(docs.select(text).mapInArrow(bodies, "cid long, body binary").dropDuplicates(["cid"]), "class-texts")


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("a", "b")).alias("c")).distinct()


def verified(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs (a, b) of class ids whose sets link, compared on the texts."""
    both = pairs.join(texts.select(F.col("cid").alias("a"), F.col("body").alias("x")), "a").join(texts.select(F.col("cid").alias("b"), F.col("body").alias("y")), "b").select("a", "b", "x", "y")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, SLICE):
                part = batch.slice(i, SLICE)
                a, b = part.column(0).to_pylist(), part.column(1).to_pylist()
                packed = dict(zip(a, part.column(2).to_pylist(), strict=True)) | dict(zip(b, part.column(3).to_pylist(), strict=True))
                sets = {}
                names = list(packed)
                for lo, hi, tokens, first, _ in _set_blocks(pa.array([unpack_text(packed[c]) for c in names], pa.large_string())):
                    sets |= {names[lo + j]: tokens[first[j] : first[j + 1]] for j in range(hi - lo)}
                linked = []
                for x, y in zip(a, b, strict=True):
                    small, large = sorted((sets[x], sets[y]), key=len)
                    common = int((large[np.minimum(np.searchsorted(large, small), len(large) - 1)] == small).sum()) if len(large) else 0
                    linked.append(common > 0 and 100 * common >= PERCENT * (len(small) + len(large) - common))
                yield part.select(["a", "b"]).filter(pa.array(linked, pa.bool_()))

    return saved(both.mapInArrow(compare, "a long, b long"), "links")


def apart(pairs: DataFrame, labels: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """The pairs whose ends aren't yet known to be connected."""
    side = lambda c: labels.select(F.col("node").alias(c), F.col("label").alias(f"label_{c}"))
    both = pairs.join(side(a), a, "left").join(side(b), b, "left")
    return both.filter(F.coalesce(f"label_{a}", a) != F.coalesce(f"label_{b}", b)).select(pairs.columns)


def centre_pairs(classes: DataFrame, which: tuple[int, ...]) -> DataFrame:
    """(a, b): a class and the centre of a min-hash bucket that it is in, if their smallest tokens agree.

    Each of the min-hashes prefers other centres, so that a class has several chances.
    """
    placed = classes.filter("n > 0").select("cid", F.posexplode("keys").alias("i", "h")).filter(F.col("i").isin(*which))
    turn = F.element_at(F.array(*[F.lit(t) for t in TURNS]), F.col("i") + 1)
    turned = placed.withColumn("t", F.col("cid").bitwiseXOR(turn))
    centres = saved(turned.groupBy("i", "h").agg(F.min("t").alias("t"), F.max("t").alias("top")).filter("t <> top").select("i", "h", F.col("t").bitwiseXOR(turn).alias("b")), "centres")
    pairs = placed.join(centres, ["i", "h"]).filter("cid <> b").select(F.least("cid", "b").alias("a"), F.greatest("cid", "b").alias("b")).distinct()
    side = lambda c, low, n: classes.select(F.col("cid").alias(c), F.col("low").alias(low), F.col("n").alias(n))
    both = pairs.join(side("a", "la", "na"), "a").join(side("b", "lb", "nb"), "b")
    near = F.size(F.array_intersect("la", "lb")) >= HOPEFUL * F.least(F.size("la"), F.size("lb"))
    return both.filter(near & (100 * F.least("na", "nb") >= PERCENT * F.greatest("na", "nb"))).select("a", "b")


def chained(docs: DataFrame, text: str, classes: DataFrame, prefix: DataFrame) -> DataFrame:
    """Links of classes that are in no group so far to some of those next to them in rows of the matrix.

    In a large cluster whose sets are only just alike, most have no link to a centre, and all their
    links would come out of the matrix one by one: as many as the square of the cluster. A few for
    each set, found here, make a group of them, inside which the matrix needn't look.
    """
    some = F.filter(F.arrays_zip("tokens", "places"), lambda x, i: (i < FIRST) | (x["tokens"].bitwiseAND(F.lit(CHAINED - 1)) == 0))
    alone = prefix.filter("not many").withColumn("some", some).select("cid", "n", F.col("some.tokens").alias("tokens"), F.col("some.places").alias("places"), "parity")
    pairs = saved(promising(qualifying(matrix(alone, "cid", "cid", F.lit(False)), STEPS).select("a", "b"), classes), "chained-pairs")
    texts = class_texts(docs, text, _ends(pairs))
    links = verified(texts, pairs)
    discard(texts, pairs)
    return links


def group_links(docs: DataFrame, text: str, classes: DataFrame, passing: DataFrame, prefix: DataFrame, members: DataFrame, links: DataFrame) -> DataFrame:
    """All links found, those between opened groups included.

    One link connects two groups, and the rest between them changes nothing. So each pair of
    groups is first tried with a few members of either side. Groups that are still apart are
    opened: their members become rows of a matrix of their own, in which those of one component
    don't meet, and all pairs that its bounds let pass are compared.
    """
    alone = saved(promising(passing.filter("single").select("a", "b"), classes), "promising-pairs")
    open_ = passing.filter("not single").select("a", "b")
    inside = saved(members.join(open_.select(F.explode(F.array("a", "b")).alias("g")).distinct(), "g", "left_semi"), "inside-open")
    sized = saved(inside.join(inside.groupBy("g").agg(F.count("*").alias("m"), F.min("cid").alias("first")), "g"), "open-members")
    texts = class_texts(docs, text, _ends(alone).unionByName(sized.select(F.col("cid").alias("c"))))
    links = links.unionByName(verified(texts, alone))
    few = sized.filter(F.pmod(F.xxhash64("cid"), F.ceil(F.col("m") / FEW)) == 0)
    of = lambda g, c: few.select(F.col("g").alias(g), F.col("cid").alias(c), F.col("n").alias("n" + c))
    tried = open_.join(of("a", "x"), "a").join(of("b", "y"), "b").filter(100 * F.least("nx", "ny") >= PERCENT * F.greatest("nx", "ny"))
    links = links.unionByName(verified(texts, saved(promising(tried.select(F.col("x").alias("a"), F.col("y").alias("b")), classes), "tried-pairs")))
    labels = components(links)
    # a group answers to any of its members' label
    sided = sized.join(labels.select(F.col("node").alias("first"), "label"), "first", "left").select("g", "cid", F.coalesce("label", "first").alias("side"))
    sided = saved(sided, "open-sides")
    of_groups = sided.groupBy(F.col("g").alias("node")).agg(F.min("side").alias("label"))
    still = saved(apart(open_, of_groups), "open-groups")
    ends = still.select(F.explode(F.array("a", "b")).alias("g")).distinct()
    opened = prefix.join(sided.join(ends, "g", "left_semi").select("cid", "side"), "cid")
    pairs = qualifying(matrix(opened, "cid", "side", F.lit(False))).select("a", "b")
    links = links.unionByName(verified(texts, saved(promising(pairs, classes), "opened-pairs")))
    discard(texts, prefix)
    return links


def jaccard_components(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_shingles, component_id (the smallest key reachable by links) of every row."""
    spark = docs.sparkSession
    signed = saved(signatures(docs, key, text), "signatures")
    classes = saved(signed.filter("n > 0").groupBy("cid").agg(F.min(key).alias("least"), F.first("n").alias("n"), F.first("keys").alias("keys"), F.first("low").alias("low"), F.first("parity").alias("parity")), "classes")
    near, more = (saved(centre_pairs(classes, which), "centre-pairs") for which in ((0, 1), (2, 3)))
    texts = class_texts(docs, text, _ends(near.unionByName(more)))
    links = verified(texts, near)
    links = links.unionByName(verified(texts, apart(more, components(links))))
    discard(texts)
    grouped = components(links)
    total = classes.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("t")).first()["t"]
    heavy = spark.sparkContext.broadcast(frequent_tokens(docs, text, total))
    prefix = saved(grouped_prefixes(docs, text, heavy, grouped), "prefixes")
    rows = prefix
    found = chained(docs, text, classes, prefix)
    if not found.isEmpty():
        links = links.unionByName(found)
        grouped = components(links)
        rows = in_groups(prefix.drop("g", "many"), grouped)
    members = saved(classes.select("cid", "n").join(grouped.withColumnRenamed("node", "cid"), "cid", "left").select("cid", "n", F.coalesce("label", "cid").alias("g")), "members")
    passing = saved(qualifying(matrix(rows, "g", "g", F.col("many"))), "qualifying")
    links = group_links(docs, text, classes, passing, prefix, members, links)
    labels = components(links).withColumnRenamed("node", "cid")
    rooted = classes.select("cid", "least").join(labels, "cid", "left").withColumn("label", F.coalesce("label", "cid"))
    smallest = rooted.groupBy("label").agg(F.min("least").alias("component_id"))
    named = saved(rooted.join(smallest, "label").select(F.col("cid"), "component_id"), "class-components")
    rows = signed.select(key, F.col("n").alias("n_shingles"), "cid")
    return rows.filter("n_shingles = 0").select(key, "n_shingles", F.col(key).alias("component_id")).unionByName(rows.filter("n_shingles > 0").join(named, "cid").select(key, "n_shingles", "component_id"))


def keep_representatives(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs without those that have a near duplicate of smaller key in their component, all columns kept.

    Rows of one key are one document: they stay or go together, so exact repetitions of a row that
    stays all stay. Rows whose key is null have no smaller key and stay.
    """
    gone = saved(jaccard_components(docs, key, text).filter(F.col("component_id") < F.col(key)).select(F.col(key).alias("__gone")).distinct(), "near-duplicates")
    marked = key_filter(gone.select(F.xxhash64("__gone").alias("k")), "k")
    hashed, schema, names = docs.withColumn("__key_hash", F.xxhash64(key)), docs.schema, docs.columns

    def sift(wanted: bool) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keep = batch.filter(pa.array(passes(marked.value, batch.column(batch.num_columns - 1).to_numpy()) == wanted))
                yield pa.RecordBatch.from_arrays(keep.columns[:-1], names=names)

        return hashed.mapInArrow(run, schema)

    return sift(False).unionByName(sift(True).join(gone, F.col(key) == F.col("__gone"), "left_anti"))
