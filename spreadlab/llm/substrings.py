"""Near-duplicate passages by compact windows over token min-hashes.

Tokens are 5-word shingles. For each hash function the Cartesian tree over a text's token hashes gives
compact windows (first, least, last): every subsequence between first and last that holds the token
``least`` has its hash as signature, whatever its length. Only nodes of at least ``window`` tokens are
kept, about two for every ``window`` tokens, and travel under their signature.

Equal places of a signature link as a star to their first place, so a passage that a third of all
documents hold makes as many links as it has holders. Unlike places collide: the collisions of two
documents are joined by their ranges, and where windows of at least ``COLLISIONS`` of the ``FUNCTIONS``
hash functions collide the two ranges are compared, once a pair of documents and range. A signature of
more than ``FEW`` unlike places makes no pairs: its like places (at least ``similarity`` of a window,
Jaccard) are joined to classes within the signature. Places in one class are compared again only where a
window that can match is in no run yet, places of two classes wherever they share a window's rarest
tokens; so links number about as many as places, and every like place is reached by a link or a chain of
links through other holders of its token. A window pair at similarity s is compared with the
probability that at least ``COLLISIONS`` of ``FUNCTIONS`` coins of chance s fall so: 0.973 at 0.8.

Result: one row per document, passage and representative document, the representative's own passage
included, with ``class_id``: the least document that links reach from it, the same as if every pair of
like places were listed. Lengths and positions are in words; passages below ``least_words`` are not looked for. A
passage that only one document holds, however often, is no repeat across documents.

Defined cases: null, empty and short texts hold no passage; a null id takes no part; rows that repeat an
id are one document, that of the least text hash; ties go to the smaller id; an empty table gives no
rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.llm.common import PIECE_ROWS, RowBuffer, arrow_rows, hash_words, lower_words_of, mix64, partitions_for, shingle_hashes, table, tidy
from spreadlab.llm.components import connected_components
from spreadlab.storage import materialize

SHINGLE = 5
FUNCTIONS, COLLISIONS = 4, 2
FEW = 3
CELLS = 4096  # shared tokens times diagonals that are counted together
# the id comes first, big-endian with its sign bit turned, so that places sort by id as bytes
PLACE = np.dtype([("id", ">u8"), ("a", "<i4"), ("b", "<i4"), ("c", "<i4"), ("print", "<u4")])
SIGN = np.uint64(1 << 63)
EDGE = "p_id long, p_a int, p_b int, id long, a int, b int"
STARS = f"key long, {EDGE}, c int"
PIECE = "p_id long, id long, start int, n_tokens int, p_start int, lead int, sim double"


def tokens_of(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the texts' 5-word shingles, one text after the other, and where each text begins, with the end; a shorter text has none."""
    words = [lower_words_of(t) for t in texts]
    sizes = np.array([len(w) for w in words], np.int64)
    hashes = hash_words([w for some in words for w in some])
    if len(hashes) < SHINGLE:
        return np.zeros(0, np.uint64), np.zeros(len(texts) + 1, np.int64)
    shingles = shingle_hashes(hashes, SHINGLE)
    within = np.arange(len(shingles)) + SHINGLE <= np.repeat(np.cumsum(sizes), sizes)[: len(shingles)]
    return shingles[within], np.concatenate([[0], np.cumsum(np.maximum(sizes - SHINGLE + 1, 0))])


def window_minima(v: np.ndarray, window: int) -> np.ndarray:
    """Minimum of every window, by doubling spans."""
    out, span = v, 1
    while span * 2 <= window:
        out = np.minimum(out[:-span], out[span:])
        span *= 2
    rest = window - span
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


def compact_windows(v: np.ndarray, window: int, cuts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first, least, last) of the nodes of the Cartesian tree over each text of ``v`` that span at least ``window`` tokens.

    They are the places that are the least of some window; of equal values the earlier one is less. ``cuts``: where
    each text begins, with the end; one text if None.
    """
    cuts = np.array([0, len(v)]) if cuts is None else cuts
    if len(v) < window:
        return (np.zeros(0, np.int64),) * 3
    order = np.argsort(v, kind="stable")
    rank = np.empty(len(v), np.int64)
    rank[order] = np.arange(len(v))
    m = window_minima(rank, window)
    m = m[np.arange(len(m)) + window <= np.repeat(cuts[1:], np.diff(cuts))[: len(m)]]  # windows that lie within one text
    if not len(m):
        return (np.zeros(0, np.int64),) * 3
    least = order[m[np.flatnonzero(np.concatenate([[True], m[1:] != m[:-1]]))]]
    text = np.searchsorted(cuts, least, "right") - 1
    first, last = cuts[text].tolist(), (cuts[text + 1] - 1).tolist()
    open_, current = [], -1
    for i, (at, x, t) in enumerate(zip(least.tolist(), rank[least].tolist(), text.tolist(), strict=True)):
        if t != current:
            open_, current = [], t
        while open_ and open_[-1][0] > x:  # what bounds a kept node is smaller, spans more, and so is kept itself
            last[open_.pop()[1]] = at - 1
        if open_:
            first[i] = open_[-1][2] + 1
        open_.append((x, i, at))
    return np.array(first), least, np.array(last)


def signed_windows(tokens: np.ndarray, window: int, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(signature, a, b, c): starts a..b of the shortest subsequences, of ``window`` tokens, in each compact window of the texts, and its least place.

    The two lowest bits of a signature are the hash function's number.
    """
    keys, places = [], []
    for f in range(FUNCTIONS):
        v = mix64(tokens ^ np.uint64((f + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        first, least, last = compact_windows(v, window, cuts)
        keys.append(mix64(v[least] + np.uint64(f)) & ~np.uint64(3) | np.uint64(f))
        places.append((np.maximum(first, least - window + 1), np.minimum(least, last - window + 1), least))
    return np.concatenate(keys), *(np.concatenate(x) for x in zip(*places, strict=True))


def range_prints(tokens: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """32-bit fingerprint of tokens[a:b] for many ranges: sums of tokens mixed with their distance from the end of prefix sums."""
    with np.errstate(over="ignore"):
        power = np.cumprod(np.full(len(tokens) + 1, 0x9E3779B97F4A7C15 | 1, np.uint64))
        before = np.concatenate([[np.uint64(0)], np.cumsum(mix64(tokens) * power[: len(tokens)])])
        total = (before[b] - before[a]) * power[len(tokens) - a]  # the same for equal runs anywhere in texts of any length
        inverse = np.uint64(pow(int(power[len(tokens)]), -1, 1 << 64))
    return (mix64(total * inverse + (b - a).astype(np.uint64)) >> np.uint64(32)).astype(np.uint32)


def window_postings(docs: DataFrame, window: int) -> DataFrame:
    """(key, places): a batch's places of one signature in one row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, places = [], []
            for at in range(0, b.num_rows, PIECE_ROWS):
                ids, texts = (b.column(b.schema.get_field_index(n)).slice(at, PIECE_ROWS) for n in ("id", "text"))
                tokens, cuts = tokens_of(texts.to_pylist())
                key, a, z, c = signed_windows(tokens, window, cuts)
                if len(key):
                    text, place = np.searchsorted(cuts, c, "right") - 1, np.empty(len(key), PLACE)
                    place["id"], place["print"] = ids.to_numpy()[text].view(np.uint64) ^ SIGN, range_prints(tokens, a, z + window)
                    place["a"], place["b"], place["c"] = a - cuts[text], z - cuts[text], c - cuts[text]
                    keys.append(key)
                    places.append(place)
            if not keys:
                continue
            key, place = np.concatenate(keys), np.concatenate(places).astype(PLACE)  # concatenate turns to the machine's byte order
            order = np.lexsort((place["a"], place["id"], key))
            key, place = key[order], place[order]
            starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            packed, size = place.tobytes(), PLACE.itemsize
            ends = np.concatenate([starts[1:], [len(key)]])
            yield pa.RecordBatch.from_arrays([pa.array(key[starts].view(np.int64)), pa.array([packed[x * size : y * size] for x, y in zip(starts.tolist(), ends.tolist(), strict=True)], pa.binary())], ["key", "places"])

    return docs.mapInArrow(tidy(run), "key long, places binary")


def stars(postings: DataFrame) -> DataFrame:
    """Exact edges of each signature's equal places to their first, and the unlike places that are to be compared.

    Places of one signature with equal tokens are one class and link to its first place. A signature
    of several classes gives a row without p_id for the first place of each; where one document is
    first in several classes, also the first place of another document.
    """
    schema = pa.schema([("key", pa.int64()), *((n, pa.int64() if n.endswith("id") else pa.int32()) for n in ("p_id", "p_a", "p_b", "id", "a", "b", "c"))])

    def ids(place: np.ndarray) -> np.ndarray:
        return (place["id"].astype(np.uint64) ^ SIGN).view(np.int64)

    def rows(key: np.ndarray, own: np.ndarray, centre: np.ndarray | None) -> pa.RecordBatch:
        none = [pa.nulls(len(key), f.type) for f in list(schema)[1:4]]
        sides = [[pa.array(ids(x)), *(pa.array(x[n].astype(np.int32)) for n in ("a", "b"))] for x in (own, *([] if centre is None else [centre]))]
        return pa.RecordBatch.from_arrays([pa.array(key), *(none if centre is None else sides[1]), *sides[0], pa.array(own["c"].astype(np.int32))], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_key, kept, linked = np.zeros(0, np.int64), np.zeros(0, PLACE), np.zeros(0, bool)

        def settle(k: np.ndarray, p: np.ndarray, done: np.ndarray, last: bool) -> tuple[list[pa.RecordBatch], tuple]:
            length = p["b"].astype(np.int64) - p["a"]
            order = np.lexsort((np.arange(len(k)), p["print"], length, k))
            k, p, done, length = k[order], p[order], done[order], length[order]
            new = np.concatenate([[True], (k[1:] != k[:-1]) | (length[1:] != length[:-1]) | (p["print"][1:] != p["print"][:-1])])
            first = np.flatnonzero(new)[np.cumsum(new) - 1]
            other = p["id"] != p["id"][first]
            out, edge = [], other & ~done
            if edge.any():
                out.append(rows(k[edge], p[edge], p[first[edge]]))
            # the first place of another document in each class
            second = np.zeros(len(k), bool)
            at = np.flatnonzero(other)
            second[at[np.unique(first[at], return_index=True)[1]]] = True
            held = new | second
            stay = held & (k == k[-1]) if not last and len(k) else np.zeros(len(k), bool)
            stays = order.argsort()  # back to the order of arrival
            on = k[-1] if not last else None
            full = held if last else held & (k != on)
            heads = np.flatnonzero(full & new)
            if len(heads):
                _, at_key, classes = np.unique(k[heads], return_inverse=True, return_counts=True)
                pair = np.stack([k[heads], p["id"][heads].astype(np.uint64).view(np.int64)], 1)
                _, at_pair, same = np.unique(pair, axis=0, return_inverse=True, return_counts=True)
                many, twice = np.zeros(len(k), bool), np.zeros(len(k), bool)
                many[heads], twice[heads] = classes[at_key] > 1, same[at_pair.ravel()] > 1
                open_ = full & many[first] & (new | twice[first])
                if open_.any():
                    out.append(rows(k[open_], p[open_], None))
            picked = stays[stay[stays]]
            return out, (k[picked], p[picked], np.ones(len(picked), bool))

        for b in batches:
            raw = b.column(1).to_pylist()
            if not raw:
                continue
            place = np.frombuffer(b"".join(raw), PLACE)
            key = np.repeat(b.column(0).to_numpy(), [len(r) // PLACE.itemsize for r in raw])
            out, (kept_key, kept, linked) = settle(np.concatenate([kept_key, key]), np.concatenate([kept.astype(PLACE), place]).astype(PLACE), np.concatenate([linked, np.zeros(len(key), bool)]), False)
            yield from out
        if len(kept_key):
            yield from settle(kept_key, kept.astype(PLACE), linked, True)[0]

    dealt = postings.repartition(partitions_for(postings), "key").sortWithinPartitions("key", "places")
    return dealt.mapInArrow(tidy(run), STARS)


def by_pair(edges: DataFrame, window: int) -> DataFrame:
    """(p_id, p_a, p_b, id, a, b): exact edges of one pair of documents, those that touch on one diagonal made one."""
    dealt = edges.withColumn("shift", F.col("p_a") - F.col("a")).repartition(partitions_for(edges), "p_id", "id").sortWithinPartitions("p_id", "id", "shift", "a")
    schema = pa.schema([(n, pa.int64() if n.endswith("id") else pa.int32()) for n in ("p_id", "p_a", "p_b", "id", "a", "b")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, at = None, [0, 0]
        for batch in batches:
            rows: list[tuple] = []
            for p_id, doc_id, shift, a, b in arrow_rows([batch], "p_id", "id", "shift", "a", "b"):
                if (p_id, doc_id, shift) == key and a <= at[1] + window:
                    at[1] = max(at[1], b)
                    continue
                if key is not None:
                    rows.append((key[0], at[0] + key[2], at[1] + key[2], key[1], *at))
                key, at = (p_id, doc_id, shift), [a, b]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
        if key is not None:
            last = (key[0], at[0] + key[2], at[1] + key[2], key[1], *at)
            yield pa.RecordBatch.from_arrays([pa.array([c], f.type) for c, f in zip(last, schema, strict=True)], schema=schema)

    return dealt.mapInArrow(tidy(run), EDGE)


def joined_ranges(collisions: list[tuple[int, int, int, int, int, int, int]], window: int, need: int = COLLISIONS) -> list[tuple[int, int, int, int]]:
    """(a, b, p_a, p_b): window starts of two texts where at least ``need`` hash functions collide.

    collisions(function, p_a, p_b, p_c, a, b, c): two places of one signature; the windows that collide lie
    on the diagonal of the least places. Ranges that lie within a window of each other are one.
    """
    spans = []
    for f, p_a, p_b, p_c, a, b, c in collisions:
        low, high = max(a, p_a - (p_c - c)), min(b, p_b - (p_c - c))
        if low <= high:
            spans.append((low, high, f, p_c - c))
    events = sorted([(low, 0, f) for low, _, f, _ in spans] + [(high + 1, 1, f) for _, high, f, _ in spans])
    held, ranges, begun = [0] * FUNCTIONS, [], None
    for at, end, f in events:
        held[f] += -1 if end else 1
        if sum(map(bool, held)) >= need:
            begun = at if begun is None else begun
        elif begun is not None:
            if at > begun:
                if ranges and begun <= ranges[-1][1] + window:
                    ranges[-1][1] = at - 1
                else:
                    ranges.append([begun, at - 1])
            begun = None
    out = []
    for a, b in ranges:
        shifts = [s for low, high, _, s in spans if low <= b and high >= a]
        out.append((a, b, max(0, a + min(shifts)), b + max(shifts)))
    return out


def pair_ranges(open_: DataFrame, window: int) -> DataFrame:
    """(key, id, a, b): two places of each range of two documents in which enough functions collide; key is the pair's."""
    one = open_.filter("a IS NOT NULL")
    other = one.select(F.col("key").alias("p_key"), F.col("id").alias("p_id"), F.col("a").alias("p_a"), F.col("b").alias("p_b"), F.col("c").alias("p_c"))
    met = one.join(other, (F.col("key") == F.col("p_key")) & (F.col("p_id") < F.col("id")))
    collisions = met.groupBy("p_id", "id").agg(F.collect_list(F.struct(F.col("key").bitwiseAND(3).alias("f"), "p_a", "p_b", "p_c", "a", "b", "c")).alias("met")).filter(F.size("met") >= COLLISIONS)
    schema = pa.schema([("key", pa.int64()), ("id", pa.int64()), ("a", pa.int32()), ("b", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = RowBuffer(schema)
        for p_id, doc_id, met in arrow_rows(batches, "p_id", "id", "met"):
            for a, b, p_a, p_b in joined_ranges([tuple(m.values()) for m in met], window):
                key = xxhash.xxh3_64_intdigest(b"%d %d %d %d" % (p_id, doc_id, a, p_a)) - (1 << 63)
                out.add(key, p_id, p_a, p_b)
                if out.add(key, doc_id, a, b):
                    yield out.take()
        if len(out):
            yield out.take()

    return collisions.mapInArrow(tidy(run), "key long, id long, a int, b int")


def least_common(window: int, similarity: float) -> int:
    """Tokens that two windows of the given similarity share at least."""
    return int(np.ceil(2 * window * similarity / (1 + similarity) - 1e-9))


def matching_runs(own: np.ndarray, centre: np.ndarray, window: int, similarity: float, taken: np.ndarray | None = None) -> tuple[list[tuple[int, int, int, int, float]], np.ndarray]:
    """[(start, tokens, centre start, lead, similarity)] of every run of own windows that match the centre's, on each diagonal; the
    best similarity of each own window (0 where none matches). ``taken``: flags that are set for the centre's windows that match.

    A window matches where its Jaccard with the window at the same place of the diagonal reaches the
    threshold. Runs begin and end with a shared token, ``lead`` after their first window's start.
    """
    best = np.zeros(len(own) - window + 1)
    order = np.argsort(centre, kind="stable")
    c = centre[order]
    low, high = np.searchsorted(c, own), np.searchsorted(c, own, "right")
    mine = np.flatnonzero(high > low)
    need = least_common(window, similarity)
    if len(mine) < need:
        return [], best
    low, high = low[mine], high[mine]
    repeats = bool((high - low > 1).any())
    if repeats:  # every pair of equal tokens counts for its diagonal, some million at a time
        times, votes = high - low, np.zeros(len(own) + len(centre), np.int64)
        for part in np.array_split(np.arange(len(mine)), 1 + int(times.sum() >> 22)):
            nth = np.arange(times[part].sum()) - np.repeat(np.cumsum(times[part]) - times[part], times[part])
            votes += np.bincount(order[np.repeat(low[part], times[part]) + nth] - np.repeat(mine[part], times[part]) + len(own), minlength=len(votes))
        shifts = np.flatnonzero(votes)
        shifts, counts = shifts - len(own), votes[shifts]
    else:
        shifts, counts = np.unique(order[low] - mine, return_counts=True)
    # diagonals on which both texts have a whole window
    room = np.maximum(0, -shifts) <= np.minimum(len(own), len(centre) - shifts) - window
    shifts, counts = shifts[room], counts[room]
    # a window that lacks few of its shingles is broken in two places at most, so a third lies on one diagonal
    shifts = shifts[counts >= need // 3][np.argsort(-counts[counts >= need // 3], kind="stable")]
    width = len(centre) + 1
    sorted_places = np.searchsorted(c, c) * width + order if repeats else None
    found, met = [], np.zeros(len(centre) - window + 1, bool)
    at_once, wide = max(1, CELLS // len(mine)), len(own) + 2 * window + 2  # small texts' diagonals are counted together
    for nth, d in enumerate(shifts.tolist()):
        if nth % at_once == 0:
            near, counted = None, shifts[nth : nth + at_once, None]
        first, last = max(0, -d), min(len(own), len(centre) - d) - window
        if repeats and best[first : last + 1].min() == 1 and met[first + d : last + d + 1].all():
            continue  # a period's further diagonals: both sides have met equal windows
        if near is None:
            theirs = order[low]
            if repeats:
                want = low * width + np.clip(mine + counted, 0, width - 1)
                at = np.searchsorted(sorted_places, want)
                after, before = np.minimum(at, high - 1), np.maximum(at - 1, low)
                theirs = np.where(np.abs(order[after] - mine - counted) <= np.abs(order[before] - mine - counted), order[after], order[before])
            off = theirs - mine - counted
            near = np.abs(off) < window
            row, column = np.nonzero(near)
            off, base = off[near], row * wide
            begin, end = (base + np.maximum(mine[column] + o - up, 0) for o, up in ((np.maximum(off, 0), window - 1), (np.minimum(off, 0), -1)))
            step = np.bincount(begin, minlength=len(counted) * wide) - np.bincount(end, minlength=len(counted) * wide)
            sums = np.cumsum(step.reshape(-1, wide), axis=1)
        x, common = mine[near[nth % at_once]], sums[nth % at_once, first : last + 1]
        score = common / (2 * window - common)
        good = np.flatnonzero(score >= similarity - 1e-12)
        if not len(good):
            continue
        best[good + first] = np.maximum(best[good + first], score[good])
        met[good[score[good] == 1] + first + d] = True
        if taken is not None:
            taken[good + first + d] = True
        for part in np.split(good, np.flatnonzero(np.diff(good) > window) + 1):
            a, z = int(part[0]) + first, int(part[-1]) + first + window
            held = x[np.searchsorted(x, a) : np.searchsorted(x, z)]
            start, stop = int(held[0]), int(held[-1]) + 1
            found.append((start, stop - start, start + d, start - a, float(score[part].max())))
    return found, best


def covered(sums: np.ndarray, window: int) -> np.ndarray:
    """Sums of each window of each row, of a matrix of flags."""
    total = np.zeros((len(sums), sums.shape[1] + 1), np.int32)
    np.cumsum(sums, axis=1, out=total[:, 1:])
    return total[:, window:] - total[:, :-window]


def families(ids: list[int], slices: list[np.ndarray], window: int, similarity: float) -> list[tuple[int, int, tuple[int, int, int, int, float]]]:
    """(place, earlier place, run) of like windows, so many that like places are joined, by one run or by a chain of runs.

    Two places that chains of runs join already are compared again only while one of them has a window that no
    run covers; so neither a class nor the extent of a passage is lost, and runs number about as many as places.
    A place is first compared with all others at once on the diagonal of their common token. What that leaves
    open, between classes and in windows that nothing covers, is compared where places can hold like windows:
    windows that match share one of their rarest tokens, so tokens that the whole group holds choose nothing.
    """
    if len(slices) == 2:
        return [(1, 0, piece) for piece in matching_runs(slices[1], slices[0], window, similarity)[0]] if ids[0] != ids[1] else []
    group = Group(ids, slices, window, similarity)
    group.meet_leaders()
    group.meet_rest()
    return sorted(group.found)


class Group:
    """Places of one signature while they are compared: classes so far, and windows that can match but are in no run yet."""

    def __init__(self, ids: list[int], slices: list[np.ndarray], window: int, similarity: float):
        self.ids, self.slices, self.window, self.similarity = np.array(ids), slices, window, similarity
        self.need, self.found, m = least_common(window, similarity), [], len(slices)
        self.sizes = np.array([len(x) for x in slices])
        place = np.repeat(np.arange(m), self.sizes)
        values, inverse, counts = np.unique(np.concatenate(slices), return_inverse=True, return_counts=True)
        rank = np.empty(len(values), np.int32)
        rank[np.lexsort((values, counts))] = np.arange(len(values), dtype=np.int32)
        ranks, n = rank[inverse], len(values)  # rarer tokens come first
        self.matrix = np.full((m, self.sizes.max()), n, np.int32)
        self.matrix[place, np.arange(len(place)) - np.repeat(np.cumsum(self.sizes) - self.sizes, self.sizes)] = ranks
        held = np.sort(ranks.astype(np.int64) * m + place)
        holders = np.bincount(held[np.concatenate([[True], held[1:] != held[:-1]])] // m, minlength=n + 1)
        self.shared = holders > 1  # tokens of two places or more
        self.able = covered(self.shared[self.matrix], window) >= self.need  # windows that any other place can match
        self.able &= np.arange(self.able.shape[1]) <= self.sizes[:, None] - window
        self.open, self.family = self.able.copy(), np.arange(m)
        hub = self.matrix == holders.argmax()
        self.hub_at = np.where(hub.any(axis=1), hub.argmax(axis=1), -1)
        self.where = np.full(n + 1, -1, np.int32)

    def meet_leaders(self) -> None:
        """Compare first places with all later ones that have an open window, while that settles a good part of them."""
        misses = 0
        for c in np.flatnonzero(self.able.any(axis=1)).tolist():
            if not self.open[c].any():
                continue
            rows = c + 1 + np.flatnonzero(self.open[c + 1 :].any(axis=1) & (self.ids[c + 1 :] != self.ids[c]))
            if not len(rows):
                return
            misses += self.meet(c, rows, False) * 32 < len(rows)
            if misses == 4:
                return

    def meet_rest(self) -> None:
        """Compare what can still join two classes or cover an open window."""
        alive = np.flatnonzero(self.able.any(axis=1))
        kin, bare_rows = self.family[alive], np.flatnonzero(self.open.any(axis=1))
        if not len(bare_rows) and (kin == kin[:1]).all():
            return
        cells, kin = self.matrix[alive], np.repeat(kin, self.matrix.shape[1])
        least, most = np.full(len(self.shared), len(self.ids)), np.full(len(self.shared), -1)
        np.minimum.at(least, cells.ravel(), kin)
        np.maximum.at(most, cells.ravel(), kin)
        between = (least < most) & self.shared  # tokens of two classes
        able = covered(between[cells], self.window) >= self.need
        if len(bare_rows):
            bare = np.zeros(len(self.shared), bool)
            row, at = np.nonzero(self.open[bare_rows])
            bare[self.matrix[bare_rows[row][:, None], at[:, None] + np.arange(self.window)]] = True
            able |= covered((bare & self.shared)[cells], self.window) >= self.need
        able &= self.able[alive]  # windows that another class or an open window can match
        alive, able = alive[some := able.any(axis=1)], able[some]
        if len(alive) < 2:
            return
        rarest, posts = self.window - self.need + 1, []
        for nth in np.array_split(np.arange(len(alive)), 1 + len(alive) // 128):
            part = alive[nth]
            row, at = np.nonzero(able[nth])
            low = np.partition(np.lib.stride_tricks.sliding_window_view(self.matrix[part], self.window, axis=1)[row, at], rarest - 1, axis=1)[:, :rarest]
            keep = self.shared[low]
            row, bare = (np.broadcast_to(x[:, None], low.shape)[keep] for x in (part[row], self.open[part][row, at]))
            key = np.unique((low[keep].astype(np.int64) * len(self.ids) + row) * 2 + ~bare)
            posts.append(key[np.concatenate([[True], key[1:] // 2 != key[:-1] // 2])[: len(key)]])
        key = np.concatenate(posts) if posts else np.zeros(0, np.int64)
        token, place, bare = key // 2 // len(self.ids), key // 2 % len(self.ids), key % 2 == 0
        order = np.lexsort((place, self.family[place], token))
        token, place, bare = token[order], place[order], bare[order]
        if not len(token):
            return
        kin = self.family[place]
        cut = np.concatenate([[True], token[1:] != token[:-1]])
        split = cut | np.concatenate([[True], kin[1:] != kin[:-1]])
        ends = [(np.flatnonzero(x)[np.cumsum(x) - 1], np.append(np.flatnonzero(x)[1:], len(x))[np.cumsum(x) - 1]) for x in (cut, split)]
        (low, high), (kin_low, kin_high) = ends
        bares = np.flatnonzero(bare)
        bare_low, bare_high = np.searchsorted(bares, low), np.searchsorted(bares, high)
        # posts that another class or an open window can meet
        live = np.flatnonzero((high - low > 1) & ((kin_low > low) | (kin_high < high) | (bare_high > bare_low)))
        live = live[np.argsort(place[live], kind="stable")]
        cuts = np.searchsorted(place[live], np.arange(len(self.ids) + 1))
        for c in np.unique(place[live]).tolist():
            parts = []
            for x in live[cuts[c] : cuts[c + 1]].tolist():
                if bare[x]:
                    parts.append(place[low[x] : high[x]])
                else:
                    parts += [place[low[x] : kin_low[x]], place[kin_high[x] : high[x]], place[bares[bare_low[x] : bare_high[x]]]]
            rows = np.unique(np.concatenate(parts))
            rows = rows[(rows > c) & (self.ids[rows] != self.ids[c])]
            rows = rows[(self.family[rows] != self.family[c]) | self.open[rows].any(axis=1) | self.open[c].any()]
            if len(rows):
                self.meet(c, rows, True)

    def meet(self, c: int, rows: np.ndarray, whole: bool) -> int:
        """Runs of later places with place c on the diagonal of their common token, and if ``whole`` on all others where they are needed; how many rows were settled by the former."""
        return sum(self.meet_some(c, part, whole) for part in np.array_split(rows, 1 + len(rows) // 4096))

    def meet_some(self, c: int, rows: np.ndarray, whole: bool) -> int:
        window, own = self.window, self.matrix[c, : self.sizes[c]]
        self.where[own] = np.arange(len(own), dtype=np.int32)
        theirs = self.where[self.matrix[rows]]
        self.where[own] = -1
        can = self.able[rows] & (covered(theirs >= 0, window) >= self.need)  # windows that have enough of c's tokens
        some = can.any(axis=1)
        rows, theirs, can = rows[some], theirs[some], can[some]
        if not len(rows):
            return 0
        good, hits = np.zeros_like(can), 0
        if self.matrix.shape[1] < 2 * window and self.hub_at[c] >= 0:
            good, hits = self.diagonal(c, rows, theirs)
        if whole:
            can &= ~good
            for nth in np.flatnonzero(can.any(axis=1)).tolist():
                row, maybe = int(rows[nth]), can[nth]
                apart = self.family[row] != self.family[c]
                if apart or (maybe & self.open[row]).any() or (self.open[c].any() and (self.open[c] & self.holds(c, row)).any()):
                    self.meet_pair(c, row)
        return hits

    def holds(self, c: int, row: int) -> np.ndarray:
        """Windows of place c that have enough of the other place's tokens."""
        return covered(np.isin(self.matrix[c], self.matrix[row, : self.sizes[row]])[None], self.window)[0] >= self.need

    def diagonal(self, c: int, rows: np.ndarray, theirs: np.ndarray) -> tuple[np.ndarray, int]:
        """Windows of the rows that match c's on the common token's diagonal, and how many rows' runs are kept, as they join or cover
        something. ``theirs``: c's place of each token, or -1."""
        window, width = self.window, self.matrix.shape[1]
        shift, spot = (self.hub_at[c] - self.hub_at[rows])[:, None].astype(np.int32), np.arange(width, dtype=np.int32)
        off = theirs - spot - shift
        near = (theirs >= 0) & (np.abs(off) < window)
        row, at = np.nonzero(near)
        off, base = off[near], row * (width + 1)
        begin, end = (base + np.maximum(at + o - up, 0) for o, up in ((np.maximum(off, 0), window - 1), (np.minimum(off, 0), -1)))
        step = np.bincount(begin, minlength=len(rows) * (width + 1)) - np.bincount(end, minlength=len(rows) * (width + 1))
        common = np.cumsum(step.reshape(-1, width + 1), axis=1)[:, : width - window + 1]
        start = spot[: width - window + 1]
        good = (common >= self.need) & (start >= -shift) & (start <= np.minimum(self.sizes[rows][:, None], self.sizes[c] - shift) - window)
        good &= (self.hub_at[rows] >= 0)[:, None]
        new = good.any(axis=1) & (self.family[rows] != self.family[c]) | (good & self.open[rows]).any(axis=1)
        if self.open[c].any():
            new |= (good & self.open[c][np.clip(start + shift, 0, len(start) - 1)]).any(axis=1)
        hit = np.flatnonzero(new)
        if not len(hit):
            return good, 0
        wins, shift, where = good[hit], shift[hit, 0], rows[hit]
        first, last = wins.argmax(axis=1), wins.shape[1] - 1 - wins[:, ::-1].argmax(axis=1)
        inside = near[hit] & (spot >= first[:, None]) & (spot < (last + window)[:, None])
        begun, ended = inside.argmax(axis=1), width - inside[:, ::-1].argmax(axis=1)
        best = np.where(wins, common[hit], 0).max(axis=1)
        best = best / (2 * window - best)
        runs = zip(begun.tolist(), (ended - begun).tolist(), (begun + shift).tolist(), (begun - first).tolist(), best.tolist(), strict=True)
        self.found += [(h, c, run) for h, run in zip(where.tolist(), runs, strict=True)]
        self.open[where] &= (start < first[:, None]) | (start > last[:, None])
        step = np.bincount(first + shift, minlength=width + 1) - np.bincount(last + shift + 1, minlength=width + 1)
        self.open[c] &= np.cumsum(step)[: width - window + 1] == 0
        self.join(c, where)
        return good, len(hit)

    def meet_pair(self, c: int, row: int) -> None:
        """Runs of two places on every diagonal."""
        taken = np.zeros(self.open.shape[1], bool)
        runs, best = matching_runs(self.slices[row], self.slices[c], self.window, self.similarity, taken)
        own, theirs = np.zeros(self.sizes[row], bool), np.zeros(self.sizes[c], bool)
        for run in runs:  # a period's further diagonals cover nothing more
            spans = own[run[0] : run[0] + run[1]], theirs[max(run[2], 0) : run[2] + run[1]]
            if not all(x.all() for x in spans):
                self.found.append((row, c, run))
                for x in spans:
                    x[:] = True
        self.open[row, : len(best)] &= best == 0
        self.open[c] &= ~taken
        if runs:
            self.join(c, np.array([row]))

    def join(self, c: int, rows: np.ndarray) -> None:
        """One class of the classes of these places."""
        if (other := np.unique(self.family[rows])).tolist() != [self.family[c]]:
            self.family[np.isin(self.family, other)] = self.family[c]


def compared(places: DataFrame, docs: DataFrame, window: int, similarity: float) -> DataFrame:
    """(p_id, id, start, n_tokens, p_start, lead, sim): like passages among the unlike places of each signature."""
    wanted = materialize(places.groupBy(F.col("id").alias("w_id")).agg(F.collect_list(F.struct("key", "a", "b")).alias("ranges")), "passage-ranges")
    # a merge join at every size: what holds passages grows with the corpus
    holders = docs.join(wanted.hint("merge"), F.col("id") == F.col("w_id")).dropDuplicates(["id"])
    schema = pa.schema([("key", pa.int64()), ("id", pa.int64()), ("a", pa.int32()), ("tokens", pa.binary())])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, PIECE_ROWS):
                ids, texts, ranges = (b.column(b.schema.get_field_index(n)).slice(at, PIECE_ROWS) for n in ("id", "text", "ranges"))
                tokens, cuts = tokens_of(texts.to_pylist())
                tokens = (tokens >> np.uint64(32)).astype("<u4")
                text, (key, a, z) = np.repeat(np.arange(len(ids)), pc.list_value_length(ranges).to_numpy(zero_copy_only=False)), (ranges.flatten().field(n).to_numpy() for n in ("key", "a", "b"))
                size = cuts[text + 1] - cuts[text]
                held = np.flatnonzero(a + window <= size)
                text, key, a, z = text[held], key[held], a[held], np.minimum(z[held] + window, size[held])
                packed = tokens.tobytes()
                cells = [packed[x:y] for x, y in zip((4 * (cuts[text] + a)).tolist(), (4 * (cuts[text] + z)).tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(ids.to_numpy()[text]), pa.array(a.astype(np.int32)), pa.array(cells, pa.binary())], schema=schema)

    slices = holders.select("id", "text", "ranges").mapInArrow(tidy(cut), "key long, id long, a int, tokens binary")
    dealt = slices.repartition(partitions_for(slices), "key").sortWithinPartitions("key", "id", "a")
    out_schema = pa.schema([("p_id", pa.int64()), ("id", pa.int64()), ("start", pa.int32()), ("n_tokens", pa.int32()), ("p_start", pa.int32()), ("lead", pa.int32()), ("sim", pa.float64())])

    def settle(group: list[tuple]) -> list[tuple]:
        ids, at = [x[0] for x in group], [x[1] for x in group]
        return [(ids[c], ids[h], at[h] + s, n, at[c] + p, lead, sim) for h, c, (s, n, p, lead, sim) in families(ids, [np.frombuffer(x[2], np.uint32) for x in group], window, similarity)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, group, rows = None, [], []
        for b in batches:
            for key, *place in arrow_rows([b], "key", "id", "a", "tokens"):
                if key != current:
                    rows += settle(group) if len(group) > 1 else []
                    current, group = key, []
                group.append(tuple(place))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), out_schema, strict=True)], schema=out_schema)
                rows = []
        if rows := settle(group) if len(group) > 1 else []:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), out_schema, strict=True)], schema=out_schema)

    return dealt.mapInArrow(tidy(run), PIECE)


def repeated_passages(docs: DataFrame, least_words: int = 50, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, start_word, n_words, rep_id, rep_start_word, similarity, is_representative, class_id)."""
    window = least_words - SHINGLE + 1
    rows = one_text_each(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).filter("id IS NOT NULL"))
    met = materialize(stars(window_postings(rows, window)), "passage-stars")
    same = by_pair(met.filter("p_id IS NOT NULL").drop("key", "c"), window)
    whole = same.select("p_id", "id", F.col("a").alias("start"), (F.col("b") - F.col("a") + window).alias("n_tokens"), F.col("p_a").alias("p_start"), F.lit(0).alias("lead"), F.lit(1.0).alias("sim"))
    unlike = met.filter("p_id IS NULL").select("key", "id", "a", "b", "c")
    many = materialize(unlike.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > FEW).select(F.col("key").alias("many")), "passage-many")
    few = unlike.join(many, F.col("key") == F.col("many"), "left_anti")
    places = pair_ranges(few, window).unionByName(unlike.join(many, F.col("key") == F.col("many"), "left_semi").drop("c"))
    like = compared(materialize(places, "passage-places"), rows, window, similarity)
    pieces = materialize(whole.unionByName(like).distinct(), "passage-pieces")
    return with_class(merge_passages(pieces, window), pieces)


def with_class(passages: DataFrame, pieces: DataFrame) -> DataFrame:
    """Passages with ``class_id``: the least document that their document's links reach, itself included."""
    links = materialize(pieces.select(F.col("p_id").alias("a"), F.col("id").alias("b")).distinct(), "passage-links")
    classes = materialize(connected_components(links), "passage-classes").select(F.col("node").alias("c_id"), F.col("component").alias("class_id"))
    return passages.join(classes, F.col("id") == F.col("c_id"), "left").drop("c_id").withColumn("class_id", F.coalesce("class_id", "id"))


def one_text_each(rows: DataFrame) -> DataFrame:
    """rows(id, text) without other texts of a repeated id than that of the least hash; only ids and hashes are shuffled."""
    h = F.xxhash64(F.coalesce("text", F.lit("")))
    more = rows.select(F.col("id").alias("twice"), h.alias("h")).groupBy("twice").agg(F.min("h").alias("least"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    more = materialize(more, "passage-repeated-ids")
    if more.isEmpty():
        return rows
    return rows.join(more, F.col("id") == F.col("twice"), "left").filter(F.col("least").isNull() | (h == F.col("least"))).select("id", "text")


def merge_passages(found: DataFrame, window: int) -> DataFrame:
    """Pieces of one document and representative that meet in both become one passage; one shorter than a window is widened to the window that matched."""
    own = found.select("id", F.col("p_id").alias("rep_id"), "start", (F.col("start") + F.col("n_tokens")).alias("stop"), F.col("p_start").alias("rep_start"), "lead", "sim")
    rep = found.groupBy(F.col("p_id").alias("id"), F.col("p_start").alias("start"), "n_tokens", "lead").agg(F.max("sim").alias("sim"))
    rep = rep.select("id", F.col("id").alias("rep_id"), "start", (F.col("start") + F.col("n_tokens")).alias("stop"), F.col("start").alias("rep_start"), "lead", "sim")
    pieces = own.unionByName(rep).groupBy("id", "rep_id").agg(F.array_sort(F.collect_set(F.struct("start", "stop", "rep_start", "lead", "sim"))).alias("pieces"))
    pieces = pieces.sortWithinPartitions("id", "rep_id")
    schema = pa.schema([("id", pa.int64()), ("rep_id", pa.int64()), ("start_word", pa.int64()), ("n_words", pa.int64()), ("rep_start_word", pa.int64()), ("similarity", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for doc_id, rep_id, some in arrow_rows([b], "id", "rep_id", "pieces"):
                merged: list[list] = []
                for p in some:
                    size = p["stop"] - p["start"]
                    # pieces are one passage where they meet in both documents
                    m = next((m for m in reversed(merged) if p["start"] <= m[1] and p["rep_start"] <= m[4] and p["rep_start"] + size >= m[2]), None)
                    if m is None:
                        merged.append([p["start"], p["stop"], p["rep_start"], p["sim"], p["rep_start"] + size, p["lead"]])
                    else:
                        m[1:5] = max(m[1], p["stop"]), min(m[2], p["rep_start"]), max(m[3], p["sim"]), max(m[4], p["rep_start"] + size)
                for m in merged:
                    if m[1] - m[0] < window:
                        back = min(m[5], window - (m[1] - m[0]))
                        m[0], m[1], m[2] = m[0] - back, m[0] - back + window, m[2] - back
                out += [(doc_id, rep_id, a, z - a + SHINGLE - 1, r, s) for a, z, r, s, *_ in merged]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    merged = pieces.mapInArrow(tidy(run), "id long, rep_id long, start_word long, n_words long, rep_start_word long, similarity double")
    return merged.select("id", "start_word", "n_words", "rep_id", "rep_start_word", "similarity", (F.col("id") == F.col("rep_id")).alias("is_representative"))


def op8_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeated_passages(table(spark, sf_dir, "documents"))
    return found.withColumnRenamed("id", "doc_id").withColumnRenamed("rep_id", "rep_doc_id")


QUERIES = {"op8_substrings": op8_substrings}
