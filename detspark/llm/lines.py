"""Line deduplication: an exact set-similarity join on the word sets of lines; matches of an earlier line go.

Line b goes if an earlier line a (by document, then line number) has a word set of Jaccard similarity of at least ``SIMILARITY``.
Lines without words stay.  Equal word sets are one class, so a line that millions of documents share is one row of the join.

Words are ordered by rarity.  A similar pair shares a word among the first ``n - ceil(t n) + 1`` of both sets (prefix), sizes
are within the factor t (length), and the places of the shared words leave room for the needed overlap (position).  A
parity bitmap of the words bounds their difference once more.  Pairs that pass are verified on the whole word sets.

Rarity comes from counts of all words in a table of fixed size.  Words that share a counter are ordered by their hash; any
fixed order gives the same result, rarity only makes the join small.  Words are compared as 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.llm import text as tx
from detspark.plans.scratch import Workspace, release, staged

SIMILARITY = 0.8
COUNTERS = 1 << 18
_SLICE = 1 << 14
#: bits of a line number within its text; above them stands the rank of the row among those of its key
_LINES = 32
#: widths of a posting's fields: 20 bits of size, 11 of position; larger sizes and positions are cut, which only weakens the
#: filters
_SIZES, _PLACES = (1 << 20) - 1, (1 << 11) - 1
#: larger sets have bitmaps of 256 bits, smaller ones of 64
_LONG = 80
_BREAKS = np.zeros(256, np.uint8)
_BREAKS[10] = 1


def _tokens(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(document row, line number, word hash) of all words, lower-cased in ASCII; chunks end at line ends."""
    offsets, data = tx.column_bytes(column)
    last_row, lines_before = -1, 0
    for rows, bounds, chunk in tx.pieces(offsets, data, _BREAKS):
        lower = tx.LOWER[chunk]
        starts, ends = tx.spans(lower, tx.BLANKS, bounds)
        breaks = np.flatnonzero(chunk == 10)
        base = np.searchsorted(breaks, bounds[:-1])  # line ends before each piece
        carried = lines_before if rows[0] == last_row else 0
        shift = np.zeros(len(rows), np.int64)
        shift[rows == rows[0]] = carried
        if len(starts):
            piece = np.searchsorted(bounds, starts, side="right") - 1
            line = np.searchsorted(breaks, starts) - base[piece] + shift[piece]
            yield rows[piece], line, tx.hash_spans(lower, starts, ends)
        tail = rows == rows[-1]
        first = int(np.flatnonzero(tail)[0])
        lines_before = (lines_before if rows[-1] == last_row and rows[0] == rows[-1] else 0) + len(breaks) - int(base[first])
        last_row = rows[-1]


def rarity(docs: DataFrame, counters: int = COUNTERS) -> np.ndarray:
    """Occurrences of all words of ``docs(text)``, folded into ``counters`` cells: a table of fixed size.

    Each task adds up its own table and sends it in slices, which are added per slice.
    """
    slices = max(1, counters // _SLICE)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        total = np.zeros(counters, np.int64)
        for batch in batches:
            for _, _, word in _tokens(batch.column(0)):
                total += np.bincount((word & np.uint64(counters - 1)).astype(np.int64), minlength=counters)
        if total.any():
            parts = total.reshape(slices, -1)
            yield pa.RecordBatch.from_arrays([pa.array(range(slices), pa.int32()), pa.array([np.minimum(p, 0x7FFFFFFF).astype(np.int32).tobytes() for p in parts], pa.binary())], ["part", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for part, counts in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                got = np.frombuffer(counts.as_buffer(), np.int32).astype(np.int64)
                sums[part] = sums[part] + got if part in sums else got
        # 32 bits are enough to order by; larger counts are all the same
        rows = [(k, np.minimum(v, 0x7FFFFFFF).astype(np.int32).tobytes()) for k, v in sums.items()]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["part", "counts"])

    parts = docs.select("text").mapInArrow(count, "part int, counts binary")
    table = np.zeros((slices, counters // slices), np.int32)
    for row in parts.repartition(min(slices, 64), "part").mapInArrow(add, "part int, counts binary").collect():
        table[row["part"]] = np.frombuffer(row["counts"], np.int32)
    return table.ravel()


def prefix_length(n: np.ndarray, t: float = SIMILARITY) -> np.ndarray:
    return n - np.ceil(t * n - 1e-9).astype(np.int64) + 1


_LINE = T.StructType([T.StructField(n, t) for n, t in (("kind", T.IntegerType()), ("h1", T.LongType()), ("h2", T.LongType()), ("doc", T.LongType()), ("line", T.LongType()), ("n", T.IntegerType()), ("b0", T.LongType()), ("b1", T.LongType()), ("b2", T.LongType()), ("b3", T.LongType()), ("prefix", T.ArrayType(T.IntegerType())))])
#: kinds of rows: the first line of a word set so far, and a line that an equal one precedes
_FIRST, _REPEAT = 0, 1


def _sets(row: np.ndarray, line: np.ndarray, word: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct words of each line by rank (below 1024), then hash: (start of each line, words, their line's row and number).

    Line, rank and the upper bits of the hash are sorted as one number; where these can't tell words apart, by all of it.
    """
    unit = np.concatenate([[0], np.cumsum((np.diff(row) != 0) | (np.diff(line) != 0))])
    if unit[-1] < 1 << 20:
        key = (unit.astype(np.uint64) << np.uint64(44)) | (rank.astype(np.uint64) << np.uint64(34)) | (word >> np.uint64(30))
        order = np.argsort(key)
        key, sorted_words = key[order], word[order]
        if ((key[1:] == key[:-1]) & (sorted_words[1:] != sorted_words[:-1])).any():
            order = np.lexsort((word, rank, unit))
    else:
        order = np.lexsort((word, rank, unit))
    unit, word = unit[order], word[order]
    fresh = np.concatenate([[True], (np.diff(unit) != 0) | (word[1:] != word[:-1])])
    unit, word, at = unit[fresh], word[fresh], order[fresh]
    starts = np.flatnonzero(np.concatenate([[True], np.diff(unit) != 0]))
    return starts, word, row[at][starts], line[at][starts]


def _bitmaps(word: np.ndarray, starts: np.ndarray, n: np.ndarray) -> list[np.ndarray]:
    """Parity bitmaps: every word flips one bit of 256; sets of up to ``_LONG`` words have them folded into the first 64."""
    flips, half = np.uint64(1) << (word >> np.uint64(58)), (word >> np.uint64(40)) & np.uint64(3)
    parts = [np.bitwise_xor.reduceat(np.where(half == k, flips, np.uint64(0)), starts) for k in range(4)]
    short = n <= _LONG
    parts[0] = np.where(short, parts[0] ^ parts[1] ^ parts[2] ^ parts[3], parts[0])
    return [parts[0], *(np.where(short, np.uint64(0), b) for b in parts[1:])]


def ranks(counts: np.ndarray) -> np.ndarray:
    """Rarity ranks below 1024 from counts: rare words first, in steps of a few per cent."""
    return np.minimum(np.log2(counts.astype(float) + 1) * 32, 1023).astype(np.int64)


def _ragged(starts: np.ndarray, n: np.ndarray) -> np.ndarray:
    """starts[0] .. starts[0]+n[0]-1, then starts[1] .. and so on."""
    ends = np.cumsum(n)
    return np.repeat(starts - (ends - n), n) + np.arange(int(ends[-1]) if len(ends) else 0)


def _lists(n: np.ndarray, values: pa.Array) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(n)).astype(np.int32)), values)


def _repeats(doc: np.ndarray, line: np.ndarray) -> pa.RecordBatch:
    zero, n = np.zeros(len(doc), np.int64), np.zeros(len(doc), np.int32)
    return pa.RecordBatch.from_arrays([pa.array(n + _REPEAT), pa.array(zero), pa.array(zero), pa.array(doc), pa.array(line), pa.array(n), *[pa.array(zero)] * 4, _lists(n, pa.array([], pa.int32()))], _LINE.names)


def line_sets(docs: DataFrame, counts: np.ndarray, t: float = SIMILARITY) -> DataFrame:
    """Lines with words: two hashes, size, bitmap and prefix of the word set.

    Of equal sets in a chunk of text only the first line is passed on; the others are marked as repeats at once.
    """
    held = docs.sparkSession.sparkContext.broadcast(ranks(counts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        table = held.value
        mask = np.uint64(len(table) - 1)
        for batch in batches:
            ids, base = (batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
            for row, line, word in _tokens(batch.column(2)):
                starts, word, r, l = _sets(row, line, word, table[(word & mask).astype(np.int64)])
                n = np.diff(np.append(starts, len(word)))
                with np.errstate(over="ignore"):
                    h1 = np.add.reduceat(tx.mix(word), starts).view(np.int64)
                    h2 = np.bitwise_xor.reduceat(tx.mix(word ^ np.uint64(0xA5A5A5A5A5A5A5A5)), starts).view(np.int64)
                bitmaps = _bitmaps(word, starts, n)
                doc, l = ids[r].astype(np.int64), base[r] + l
                order = np.lexsort((l, doc, h2, h1))
                again = np.zeros(len(order), bool)
                again[1:] = (h1[order][1:] == h1[order][:-1]) & (h2[order][1:] == h2[order][:-1])
                if again.any():
                    yield _repeats(doc[order[again]], l[order[again]])
                keep = order[~again]
                p = prefix_length(n[keep], t)
                short = (word[_ragged(starts[keep], p)] >> np.uint64(20)).astype(np.uint32).view(np.int32)
                columns = [pa.array(np.zeros(len(keep), np.int32)), *(pa.array(x[keep]) for x in (h1, h2, doc, l)), pa.array(n[keep].astype(np.int32)), *(pa.array(b[keep].view(np.int64)) for b in bitmaps), _lists(p, pa.array(short))]
                yield pa.RecordBatch.from_arrays(columns, _LINE.names)

    return docs.select("_key", "_base", "text").mapInArrow(run, _LINE)


def _firsts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by set, document and line: the first of each set stays, the others are repeats."""
    tx.release()
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        h1, h2, doc, line = (batch.column(c).to_numpy() for c in ("h1", "h2", "doc", "line"))
        again = np.zeros(len(h1), bool)
        again[1:] = (h1[1:] == h1[:-1]) & (h2[1:] == h2[:-1])
        again[0] = last == (h1[0], h2[0])
        last = h1[-1], h2[-1]
        if again.any():
            yield _repeats(doc[again], line[again])
        kept = batch.filter(pa.array(~again))
        yield pa.RecordBatch.from_arrays([*kept.columns[:-1], kept.column("prefix").cast(pa.list_(pa.int32()))], _LINE.names)


_PAIR = "b_doc long, b_line long, a_doc long, a_line long, slack int"
_POST = "key long, doc long, line long, b0 long, b1 long, b2 long, b3 long"
_NAMES = ["key", "doc", "line", "b0", "b1", "b2", "b3"]


def _lines_in(part: pa.RecordBatch, field: np.ndarray) -> np.ndarray:
    """Which lines of a batch the membership filter lets through."""
    return _has(field, _line_key(part.column("doc").to_numpy(), part.column("line").to_numpy()))


def _postings(marked: np.ndarray | None, words: np.ndarray | None):
    """Lines with their prefixes → one row per prefix word: key = word, size, mark and position in one number, so that postings sort by word.

    ``marked``: a membership filter of lines, which get the mark.  ``words``: one of words; postings of words that it rules
    out are left out.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1 << 13):
                part = batch.slice(at, 1 << 13)
                prefix = part.column("prefix")
                n = np.diff(prefix.offsets.to_numpy())
                word = prefix.flatten().to_numpy().astype(np.int64)
                pos = np.arange(len(word)) - np.repeat(np.cumsum(n) - n, n)
                row = np.repeat(np.arange(len(n)), n)
                keep = np.ones(len(word), bool) if words is None else _has(words, word)
                word, pos, row = word[keep], pos[keep], row[keep]
                size = np.minimum(part.column("n").to_numpy().astype(np.int64), _SIZES)[row]
                key = (word << 32) | (size << 12) | np.minimum(pos, _PLACES)
                if marked is not None:
                    key |= (_lines_in(part, marked).astype(np.int64) << 11)[row]
                yield pa.RecordBatch.from_arrays([pa.array(key), *(pa.array(part.column(c).to_numpy()[row]) for c in _NAMES[1:])], _NAMES)

    return run


def _words_of(marked: np.ndarray):
    """Prefix words of the lines that the filter lets through: ``key``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            some = batch.filter(pa.array(_lines_in(batch, marked)))
            yield pa.RecordBatch.from_arrays([some.column("prefix").flatten().cast(pa.int64())], ["key"])

    return run


def _slack(x: tuple, a: np.ndarray, b: np.ndarray, t: float) -> np.ndarray:
    """Length, position and bitmap filters on pairs of postings of one word: by how many words the bitmaps are nearer than they must be, -1 for pairs that fail."""
    n, pos, (folded, wide) = x[2], x[3], x[4]
    na, nb = n[a], n[b]
    # every word flips one bit, so bitmaps differ in no more bits than the sets differ in words
    far = np.bitwise_count(folded[a] ^ folded[b]).astype(np.int64)
    long = np.flatnonzero((na > _LONG) & (nb > _LONG))
    if len(long):
        far[long] = np.bitwise_count(wide[a[long]] ^ wide[b[long]]).sum(1)
    need = np.ceil((na + nb) * (t / (1 + t)) - 1e-9)
    ok = (far <= na + nb - 2 * need) & (np.minimum(na, nb) >= np.maximum(na, nb) * t - 1e-9)
    ok &= 1 + np.minimum(na - pos[a] - 1, nb - pos[b] - 1) + np.minimum(pos[a], pos[b]) >= need
    return np.where(ok | (na >= _SIZES) | (nb >= _SIZES), np.maximum(na + nb - 2 * need - far, 0), -1).astype(np.int32)


def _candidates(t: float, every: bool):
    """Pairs (later line b, earlier line a) among the postings of each word, which come sorted by word.

    ``every`` false: for each b the nearest a by bitmap that passes the filters; a b is held against further blocks of lines only until one
    passes, so a large group of near copies costs little more than its size.  ``every`` true: all of them, for the lines
    whose posting is marked as open.  Postings of the word at hand are kept across batches.
    """

    def ordered(x: tuple, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(earlier, later) of each pair."""
        later = (x[0][i] < x[0][j]) | ((x[0][i] == x[0][j]) & (x[1][i] < x[1][j]))
        return np.where(later, i, j), np.where(later, j, i)

    def emit(x: tuple, a: np.ndarray, b: np.ndarray, slack: np.ndarray) -> Iterator[pa.RecordBatch]:
        if every:
            good = x[5][b] > 0
            a, b, slack = a[good], b[good], slack[good]
        elif len(b):
            order = np.lexsort((-slack, b))
            b, first = np.unique(b[order], return_index=True)
            a, slack = a[order][first], slack[order][first]
        if len(b):
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (x[0][b], x[1][b], x[0][a], x[1][a], slack)], ["b_doc", "b_line", "a_doc", "a_line", "slack"])

    def word_list(x: tuple) -> Iterator[pa.RecordBatch]:
        size = len(x[0])
        index = x[3] < x[2] - np.ceil(2 * t / (1 + t) * x[2] - 1e-9) + 1  # as for short lists
        for low in range(0, size, 512):
            b = np.arange(low, min(size, low + 512))
            if every:
                b = b[x[5][b] > 0]
            for start in range(0, size, 512):
                if not len(b):
                    break
                a = np.arange(start, min(size, start + 512))
                bb, aa = np.repeat(b, len(a)), np.tile(a, len(b))
                good = (x[0][aa] < x[0][bb]) | ((x[0][aa] == x[0][bb]) & (x[1][aa] < x[1][bb]))
                shorter = np.minimum(aa, bb)  # rows are in order of size
                good &= index[shorter]
                bb, aa = bb[good], aa[good]
                slack = _slack(x, aa, bb, t)
                good = slack >= 0
                yield from emit(x, aa[good], bb[good], slack[good])
                if not every:
                    b = np.setdiff1d(b, bb[good])

    def small_lists(x: tuple, place: np.ndarray, small: np.ndarray) -> Iterator[pa.RecordBatch]:
        """All short lists of a batch at once.  ``place`` = word and size, rising: the shorter set of a pair stands before the other,
        has 0.8 of its size at least, and shares one of its first ``n - ceil(2 t / (1 + t) n) + 1`` words."""
        n, pos = x[2], x[3]
        index = np.flatnonzero(small & (pos < n - np.ceil(2 * t / (1 + t) * n - 1e-9) + 1))
        probe = np.flatnonzero(small)
        low = np.searchsorted(place[index], (place[probe] & ~_SIZES) | np.ceil(t * n[probe] - 1e-9).astype(np.int64))
        many = np.maximum(np.searchsorted(index, probe) - low, 0)
        total = np.cumsum(many)
        at = 0
        while at < len(probe):
            to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + (1 << 18), side="right")))
            i = index[_ragged(low[at:to], many[at:to])]
            j = np.repeat(probe[at:to], many[at:to])
            slack = _slack(x, i, j, t)
            good = slack >= 0
            yield from emit(x, *ordered(x, i[good], j[good]), slack[good])
            at = to

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        held: list[np.ndarray] | None = None

        def process(c: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            key, doc, line = c[:3]
            wide = np.stack(c[3:], 1).view(np.uint64)
            x = (doc, line, (key >> 12) & _SIZES, key & _PLACES, (np.bitwise_xor.reduce(wide, 1), wide), (key >> 11) & 1)
            word = key >> 32
            start = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
            n = np.diff(np.append(start, len(word)))
            yield from small_lists(x, key >> 12, np.repeat((n > 1) & (n <= 256), n))
            for s, k in zip(start[n > 256].tolist(), n[n > 256].tolist(), strict=True):
                cut = slice(s, s + k)
                yield from word_list((doc[cut], line[cut], x[2][cut], x[3][cut], (x[4][0][cut], wide[cut]), x[5][cut]))

        for batch in batches:
            if not batch.num_rows:
                continue
            now = [c.to_numpy() for c in batch.columns]
            if held is not None:
                now = [np.concatenate([h, c]) for h, c in zip(held, now, strict=True)]
            cut = int(np.searchsorted(now[0] >> 32, now[0][-1] >> 32))
            held = [c[cut:] for c in now]
            if cut:
                yield from process([c[:cut] for c in now])
        if held is not None:
            yield from process(held)

    return run


def _bloom(keys: np.ndarray, bits: int) -> list[np.ndarray]:
    k = tx.mix(keys.view(np.uint64))
    return [((k >> np.uint64(s)) & np.uint64(bits - 1)).astype(np.int64) for s in (0, 18, 36)]


def _has(field: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which keys a membership filter lets through."""
    ok = np.ones(len(keys), bool)
    for at in _bloom(keys, 8 * len(field)):
        ok &= (field[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 > 0
    return ok


#: bits of a membership filter for each key, and the most of all, which bounds what is broadcast to 32 MB
_PER_KEY, _MOST = 16, 1 << 28


def _member(wanted: DataFrame, tasks: int = 16) -> np.ndarray:
    """A membership filter over ``wanted(key)`` or ``wanted(doc, line)``; it may say yes wrongly and never no.

    Its size follows the number of keys up to ``_MOST`` bits; beyond, it lets more through, which costs time and changes no result.
    """
    wanted = staged(wanted, "wanted")
    bits = 1 << min(_MOST.bit_length() - 1, max(16, (_PER_KEY * wanted.count()).bit_length()))

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        field, any_row = np.zeros(bits, bool), False
        for batch in batches:
            any_row = any_row or batch.num_rows > 0
            columns = [c.to_numpy() for c in batch.columns]
            for at in _bloom(columns[0] if len(columns) == 1 else _line_key(*columns), bits):
                field[at] = True
        if any_row:
            yield pa.RecordBatch.from_arrays([pa.array([np.packbits(field).tobytes()], pa.binary())], ["field"])

    field = np.zeros(bits // 8, np.uint8)
    for row in wanted.repartition(tasks).mapInArrow(mark, "field binary").toLocalIterator():
        field |= np.frombuffer(row[0], np.uint8)
    return field


def _line_key(doc: np.ndarray, line: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return tx.mix(doc.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + line.astype(np.uint64)).view(np.int64)


def _wanted_lines(column: pa.Array, ids: np.ndarray, field: np.ndarray, base: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, bytes]]:
    """Lines that the filter lets through: (rows, line numbers from the row's ``base``, their bytes joined by line ends)."""
    offsets, data = tx.column_bytes(column)
    for low in range(0, len(offsets) - 1, 256):
        high = min(len(offsets) - 1, low + 256)
        part = data[offsets[low] : offsets[high]]
        bounds = offsets[low : high + 1] - offsets[low]
        # every text ends a line, also where no line end stands
        breaks = np.flatnonzero(part == 10)
        starts = np.sort(np.concatenate([bounds[:-1], breaks + 1]), kind="stable")
        ends = np.sort(np.concatenate([breaks, bounds[1:]]), kind="stable")
        # a text has a line more than line ends; an empty last line starts where the next text does
        row = np.repeat(np.arange(high - low), np.diff(np.searchsorted(breaks, bounds)) + 1)
        line = np.arange(len(starts)) - np.searchsorted(row, row, side="left")
        if base is not None:
            line += base[low + row]
        ok = _has(field, _line_key(ids[low + row], line))
        if ok.any():
            text = b"\n".join(part[a:b].tobytes() for a, b in zip(starts[ok].tolist(), ends[ok].tolist(), strict=True))
            yield low + row[ok], line[ok], text


def _some_sets(docs: DataFrame, wanted: np.ndarray) -> DataFrame:
    """Whole word sets of the lines that the filter lets through: ``doc, line, words``."""
    held = docs.sparkSession.sparkContext.broadcast(wanted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        field = held.value
        for batch in batches:
            ids, base = (batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
            for rows, lines, text in _wanted_lines(batch.column(2), ids, field, base):
                for _, place, word in _tokens(pa.array([text], pa.binary())):
                    starts, word, _, at = _sets(np.zeros(len(place), np.int64), place, word, np.zeros(len(place), np.int64))
                    words = pa.ListArray.from_arrays(pa.array(np.append(starts, len(word)).astype(np.int32)), pa.array(word.view(np.int64)))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[rows[at]], pa.int64()), pa.array(lines[at], pa.int64()), words], ["doc", "line", "words"])

    return docs.select("_key", "_base", "text").mapInArrow(run, "doc long, line long, words array<long>")


def keyed(docs: DataFrame) -> DataFrame:
    """``docs`` with ``_key``, the id that orders lines, and ``_base``, from which the lines of a row are numbered.

    Rows without an id are ordered last, by the hash of their text.  Rows that share a key are told apart by ``_base``: their
    rank by the hash of the text, equal texts by place in the input, above the bits of line numbers.  Only such rows are
    ranked; without null or repeated ids the texts are not read for it.
    """
    key = F.coalesce(F.col("doc_id"), F.pmod(F.xxhash64("text"), F.lit(1 << 40)) + F.lit((1 << 62)))
    if docs.groupBy("doc_id").count().where("doc_id is null or count > 1").isEmpty():
        return docs.withColumn("_key", key).withColumn("_base", F.lit(0).cast("long"))
    # written with the row numbers: later scans may be split otherwise when executors come or go, and would number anew
    numbered = staged(docs.withColumn("_key", key).withColumn("_row", F.monotonically_increasing_id()), "line-docs")
    with_lines = numbered.where("text is not null")
    shared = staged(with_lines.groupBy("_key").count().where("count > 1").select("_key"), "line-keys")
    rank = F.row_number().over(Window.partitionBy("_key").orderBy("_hash", "_row")) - 1
    rows = with_lines.select("_key", "_row", F.xxhash64("text").alias("_hash")).join(shared, "_key", "left_semi")
    later = staged(rows.select("_key", "_row", F.shiftleft(rank.cast("long"), _LINES).alias("_rank")).where("_rank > 0"), "line-ranks")
    return numbered.join(later, ["_key", "_row"], "left").withColumn("_base", F.coalesce("_rank", F.lit(0))).select(*[c for c in docs.columns if c not in ("_key", "_base")], "_key", "_base")


def _verified(docs: DataFrame, pairs: DataFrame, t: float, work: Workspace) -> DataFrame:
    """``(doc, line)`` of the later lines of those pairs whose whole word sets are similar.

    Only sets of lines in pairs are formed: a membership filter of fixed size says which, inside the scan.
    """
    sides = pairs.select(F.col("a_doc").alias("doc"), F.col("a_line").alias("line")).unionByName(pairs.select(F.col("b_doc").alias("doc"), F.col("b_line").alias("line"))).distinct()

    wanted = _member(sides)
    sets = work.staged(_some_sets(docs, wanted).dropDuplicates(["doc", "line"]), "line-words")
    left = sets.select(F.col("doc").alias("a_doc"), F.col("line").alias("a_line"), F.col("words").alias("a_words"))
    right = sets.select(F.col("doc").alias("b_doc"), F.col("line").alias("b_line"), F.col("words").alias("b_words"))
    both = pairs.join(left, ["a_doc", "a_line"]).join(right, ["b_doc", "b_line"])
    shared = F.size(F.array_intersect("a_words", "b_words"))
    similar = both.where(shared >= t * (F.size("a_words") + F.size("b_words") - shared) - 1e-9)
    out = work.staged(similar.select(F.col("b_doc").alias("doc"), F.col("b_line").alias("line")).distinct(), "line-matches")
    work.drop("line-words")
    return out


def removed_lines(docs: DataFrame, t: float = SIMILARITY) -> DataFrame:
    """``docs(_key, text[, _base])`` → ``(doc, line)``, lines from the row's ``_base`` or 0, of every line that an earlier one matches; staged.

    Lines of equal word sets are found first; the first line of a set stands for it.  Then two rounds of the join: in the
    first each line gets its nearest candidate by bitmap, which settles the members of groups of near copies; in the
    second the lines that had a candidate and are still open get all of theirs.  Rows of equal key and base are one document
    whose equal line numbers are the same place.
    """
    spark = docs.sparkSession
    work = Workspace(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    docs = docs if "_base" in docs.columns else docs.withColumn("_base", F.lit(0).cast("long"))
    lines = work.staged(line_sets(docs, rarity(docs), t), "lines")
    dealt = lines.where(F.col("kind") == _FIRST).repartition(parts, "h1", "h2").sortWithinPartitions("h1", "h2", "doc", "line")
    classes = work.staged(dealt.mapInArrow(_firsts, _LINE), "line-classes")
    repeats = work.staged(lines.where(F.col("kind") == _REPEAT).select("doc", "line").unionByName(classes.where(F.col("kind") == _REPEAT).select("doc", "line")), "line-repeats")
    work.drop("lines")
    firsts = classes.where(F.col("kind") == _FIRST).select("doc", "line", "n", "b0", "b1", "b2", "b3", "prefix")

    def candidates(marked: np.ndarray | None, words: np.ndarray | None) -> DataFrame:
        every = words is not None
        posts = firsts.mapInArrow(_postings(marked, words), _POST)
        near = posts.repartition(parts, F.shiftright("key", 32)).sortWithinPartitions("key").mapInArrow(_candidates(t, every), _PAIR)
        if every:
            return near.drop("slack").distinct()
        nearest = near.groupBy("b_doc", "b_line").agg(F.max(F.struct("slack", "a_doc", "a_line")).alias("a"))
        return nearest.select("b_doc", "b_line", "a.a_doc", "a.a_line")

    first = work.staged(candidates(None, None), "line-pairs")
    release(spark)
    settled = _verified(docs, first, t, work)
    left = first.select(F.col("b_doc").alias("doc"), F.col("b_line").alias("line")).join(settled, ["doc", "line"], "left_anti")
    marked = _member(left)
    words = _member(firsts.mapInArrow(_words_of(marked), "key long"))
    second = work.staged(candidates(marked, words).join(first, ["b_doc", "b_line", "a_doc", "a_line"], "left_anti"), "line-more")
    work.drop("line-classes", "line-pairs")
    matched = settled.unionByName(_verified(docs, second, t, work))
    out = staged(repeats.unionByName(matched).distinct(), "line-removed")
    work.drop("line-repeats", "line-more", "line-matches")
    return out


def without(docs: DataFrame, removed: DataFrame) -> DataFrame:
    """``docs(…, _key, _base, text)`` with ``_gone`` (array of removed line numbers, null if none) and the text without them.

    A document whose lines all go keeps an empty text.
    """
    rank = F.shiftright(F.col("line"), _LINES)
    per_doc = removed.groupBy(F.col("doc").alias("_doc"), rank.alias("_rank")).agg(F.collect_set(F.col("line").bitwiseAND(F.lit((1 << _LINES) - 1)).cast("int")).alias("_gone"))
    joined = docs.join(per_doc, (docs["_key"] == per_doc["_doc"]) & (F.shiftright(docs["_base"], _LINES) == per_doc["_rank"]), "left").drop("_doc", "_rank")
    # the lines as a variable, which is evaluated once; array_except works by hash, so time follows the number of lines
    kept = lambda lines: F.concat_ws("\n", F.transform(F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("_gone")), lambda i: F.get(lines, i)))
    cut = F.get(F.transform(F.array(F.split("text", "\n")), kept), F.lit(0))
    return joined.withColumn("text", F.when(F.col("_gone").isNull(), F.col("text")).otherwise(cut))


def dedup(docs: DataFrame, t: float = SIMILARITY) -> DataFrame:
    """``docs`` with later matching lines taken out of ``text`` and ``n_chars`` set to its length; all rows and columns stay.

    Null texts stay null; empty texts and lines without words stay; rows with a null id take part, ordered after all others.
    Rows that repeat an id, or whole rows, are documents of their own, so the first of them keeps what they share.  Other
    columns may have any name.  An empty table stays empty.
    """
    used = "doc_id", "text"
    marked = keyed(tx.carried(docs, *used))
    out = without(marked, removed_lines(marked.select("_key", "_base", "text"), t))
    return out.select(*tx.unpacked(docs, {"n_chars": F.coalesce(F.length("text"), F.lit(0))}, used))


def op3_line_dedup(spark, sf_dir: str) -> DataFrame:
    """One row per row of ``documents``: its lines, how many of them an earlier line of the table matches, and size and checksum of the text without them.

    A null text has no lines; rows with null or repeated ids are documents of their own; an empty table gives no rows.
    """
    docs = keyed(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    lines = F.when(F.col("text").isNull(), F.lit(0)).otherwise(F.size(F.split("text", "\n")))
    counted = docs.withColumn("_lines", lines)
    out = without(counted, removed_lines(docs.select("_key", "_base", "text")))
    kept = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return out.select("doc_id", F.col("_lines").cast("long").alias("n_lines"), F.coalesce(F.size("_gone"), F.lit(0)).cast("long").alias("n_removed"), F.octet_length(kept).cast("long").alias("kept_bytes"), F.crc32(kept).alias("kept_crc32"))
