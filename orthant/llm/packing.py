"""Packing documents into sequences by bin completion with branch and bound.

Pieces of equal length are interchangeable, so the search runs on the histogram of lengths: at most ``capacity`` rows,
whatever the corpus. At each step the longest remaining length opens a sequence; the undominated fillings of the rest
are enumerated by rising waste, those that the waste bound rules out are pruned, and the chosen filling is applied to
as many sequences as its parts allow, or to one. Best-fit decreasing gives the first incumbents; a better complete solution
replaces the incumbent, and the search ends when it meets the lower bound or ``nodes`` units of work are done, the
only bound on it: with nodes to spare the number of sequences is the least possible.

Documents then find their places without meeting: pieces are numbered within (length, salt), and a number maps to a
sequence and an offset through the plan, whose size again follows the number of lengths only.

Defined results: null text is an empty document, which is its closing id alone; every document appears once; an empty
table gives no rows. Repeated rows are separate documents.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant.functions.shipping import ship

from .common import whole_text, written
from .tokens import ByteLevelTokenizer, crc, in_slices, tokenizer

CAPACITY, EOS = 2048, 0
#: Work of the search in all: a filling that it looks at, dominated ones included, is one, and so are LENGTHS lengths of an
#: enumeration that begins; the part for the incumbents, and how many of these; enumerations that stay open; pieces numbered together.
NODES, LENGTHS, FOR_INCUMBENTS, INCUMBENTS, OPEN, RANKED = 60_000, 50, 0.5, 24, 64, 4096
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def lower_bound(counts: dict[int, int], capacity: int) -> int:
    """Sequences that any packing needs: by total length, and by lengths that can't share a sequence."""
    best = -(-sum(x * n for x, n in counts.items()) // capacity)
    lengths = sorted(counts)
    for t in {x for x in lengths if 2 * x <= capacity} | {0}:
        alone = sum(n for x, n in counts.items() if x > capacity - t)
        half = [(x, n) for x, n in counts.items() if capacity - t >= x and 2 * x > capacity]
        room = sum((capacity - x) * n for x, n in half)
        small = sum(x * n for x, n in counts.items() if t <= x and 2 * x <= capacity)
        best = max(best, alone + sum(n for _, n in half) + max(0, -(-(small - room) // capacity)))
    return best


def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Incumbent: longest pieces first, each into the fullest open sequence that it fits into.

    Open sequences of one filling are handled together: a length visits the fillings by rising room, and a sequence that it
    fits into takes as many of it as fit, being the fullest from the first one on.
    """
    open_: list[tuple[int, tuple[int, ...], int]] = []  # (room, parts, how many), by rising room
    closed = []
    for x in sorted(counts, reverse=True):
        n, at = counts[x], bisect_left(open_, (x,))
        moved: list[tuple[int, tuple[int, ...], int]] = []
        while n and at < len(open_):
            room, parts, times = open_.pop(at)
            each = room // x
            full = min(times, n // each)
            more = n % each if full < times else 0
            n -= full * each + more
            moved += [(room - each * x, parts + (x,) * each, full)] * (full > 0) + [(room - more * x, parts + (x,) * more, 1)] * (more > 0)
            if times > full + (more > 0):
                moved.append((room, parts, times - full - (more > 0)))
        if n:
            each = capacity // x
            full, more = divmod(n, each)
            moved += [(capacity - each * x, (x,) * each, full)] * (full > 0) + [(capacity - more * x, (x,) * more, 1)] * (more > 0)
        for entry in moved:
            insort(open_, entry) if entry[0] else closed.append(entry)
    return [(parts, times) for _, parts, times in (*closed, *open_)]


def fillings(lengths: list[int], left: list[int], room: int, most_waste: int, work: list[int] | None = None) -> Iterator[tuple[int, tuple[int, ...] | None]]:
    """(waste, parts) of all undominated fillings of the room, by rising waste up to most_waste, longer parts first.

    lengths: falling, of which left[i] pieces remain. A filling is dominated if a piece that stays out could take the place of
    some of its parts, of at most its own length together, within the waste: the exchanged filling leaves no harder rest. For
    a dominated one parts is None. Sums that the lengths from some one on can reach are bits of a number, so no branch of the
    enumeration is a dead end. work: gets the cost of finding them.
    """
    at = [(x, min(n, room // x)) for x, n in zip(lengths, left, strict=True) if n and x <= room]
    del left
    alone = bool(at) and at[0][0] == room and most_waste >= 0
    if alone:  # one piece fills the room: nothing comes before it, and nothing dominates it
        yield 0, (room,)
    if work is not None:
        work[0] += len(at) // LENGTHS
    every, have, reach = (1 << (room + 1)) - 1, dict(at), [1]
    for i in range(len(at) - 1, -1, -1):
        (x, many), bits, k = at[i], reach[-1], 1
        if bits == every:  # every sum is reached already
            reach += [every] * (i + 1)
            break
        while many:
            step = min(k, many)
            bits |= bits << (step * x) & every
            many, k = many - step, 2 * k
        reach.append(bits)
    reach.reverse()  # reach[j]: with the lengths at[j:]
    use = sum(1 << x for x in have)
    for waste in range(min(most_waste, room) + 1):
        if not reach[0] >> (room - waste) & 1:
            continue
        # a branch: the next length to try, how many of it (0: as many as fit), sum to go, parts so far
        stack: list[tuple[int, int, int, tuple[int, ...]]] = [(0, 0, room - waste, ())]
        while stack:
            k, n, rest, parts = stack.pop()
            if not rest:
                if not alone or parts != (room,):
                    yield waste, None if _dominated(parts, use, waste, every, have) else parts
                continue
            while k < len(at) and reach[k] >> rest & 1:  # shorter lengths reach less still
                x, c = at[k]
                n = n or min(c, rest // x)
                while n and not reach[k + 1] >> (rest - n * x) & 1:
                    n -= 1
                if n:
                    stack.append((k, n - 1, rest, parts) if n > 1 else (k + 1, 0, rest, parts))
                    stack.append((k + 1, 0, rest - n * x, parts + (x,) * n))
                    break
                k += 1


def _dominated(parts: tuple[int, ...], use: int, waste: int, every: int, have: dict[int, int]) -> bool:
    """use: bits of the lengths there are; have: how many of the parts' lengths there are."""
    single, several = 0, 1  # sums of one part; of none or of two and more
    for x in parts:
        several |= (several >> 1 << 1 | single) << x
        single |= 1 << x
    out = use
    for x in set(parts):
        if parts.count(x) == have[x]:
            out &= ~(1 << x)
    if not out:
        return False

    def up_to(bits: int, width: int) -> int:
        """Every bit and the width next ones above it."""
        span = 0
        while span < width:
            step = min(span + 1, width - span)
            bits, span = bits | bits << step, span + step
        return bits

    longer = up_to(single << 1, waste - 1) if waste else 0
    return bool((up_to(several, waste) & ~1 | longer) & out & every)


@dataclass
class Plan:
    patterns: list[tuple[tuple[int, ...], int]]
    sequences: int
    bound: int
    nodes: int


Patterns = list[tuple[tuple[int, ...], int]]


def _search(counts: dict[int, int], capacity: int, best: Patterns | None, enough: int, nodes: int) -> tuple[Patterns | None, int]:
    """(the best packing found, work done): better than best, or just the first one if there is none yet.

    Depth first: the longest piece left opens a sequence, its undominated fillings are taken by rising waste, first for as
    many sequences as the pieces allow, and on the way back for one, after which the next sequence chooses anew. So every
    packing of undominated fillings lies ahead, and with nodes to spare the answer is the best one. A filling is pruned when the
    waste so far leaves no room for one sequence less than the incumbent, and a rest that was met before with no more waste.
    """
    total, seen = sum(x * n for x, n in counts.items()), 0
    any_one = best is None
    best_n = sum(counts.values()) + 1 if any_one else sum(t for _, t in best)
    lengths = sorted(counts, reverse=True)
    place, left = {x: i for i, x in enumerate(lengths)}, [counts[x] for x in lengths]
    way: Patterns = []
    met: dict[int, int] = {}
    work = [0]  # of enumerations

    def options(first: int, waste: int, after: tuple | None) -> Iterator[tuple[int, tuple[int, ...], int] | None]:
        """(waste of one, parts, times), or None for a filling that is out; after: the filling before, if it began alike."""
        own = left.copy()
        own[first] -= 1
        found = fillings(lengths, own, capacity - lengths[first], (best_n - 1) * capacity - total - waste, work)
        del own
        for w, rest in found:
            if rest is None or after is not None and (w, [-y for y in rest]) < after:
                yield None  # sequences that begin alike come in the order of their fillings
                continue
            parts = (lengths[first], *rest)
            times = min(left[place[y]] // parts.count(y) for y in set(parts))
            for t in (times, 1) if times > 1 else (1,):
                yield w, parts, t

    def move(parts: tuple[int, ...], times: int) -> None:
        for y in parts:
            left[place[y]] -= times

    # a frame: choices to come, how many came, sequences and waste so far, and what makes the choices anew
    stack: list[list] = []
    if counts and best_n > enough:
        stack.append([None, 0, 0, 0, (0, 0, None)])
    while stack and seen + work[0] < nodes and best_n > enough:
        frame = stack[-1]
        _, came, n, waste, made = frame
        if frame[0] is None:
            frame[0] = options(*made)
            for _ in range(came):
                next(frame[0], None)
        step = next(frame[0], -1)
        if step == -1:
            stack.pop()
            if way:
                parts, times = way.pop()
                move(parts, -times)
            continue
        seen, frame[1] = seen + 1, came + 1
        if step is None:
            continue
        w, parts, times = step
        # a solution with one sequence less than the incumbent wastes at most this
        now = waste + w * times
        if now > (best_n - 1) * capacity - total:
            continue
        move(parts, times)
        if not any(left):
            if n + times < best_n:
                best, best_n = [*way, (parts, times)], n + times
                if any_one:
                    break
            move(parts, -times)
            continue
        same = times == 1 and left[made[0]] > 0
        if not same:
            key = hash(tuple(left))
            if met.get(key, now + 1) <= now:
                move(parts, -times)
                continue
            met[key] = now
        way.append((parts, times))
        following = next(i for i in range(made[0], len(left)) if left[i])
        stack.append([None, 0, n + times, now, (following, now, (w, [-y for y in parts[1:]]) if same else None)])
        if len(stack) > OPEN:
            stack[-OPEN - 1][0] = None  # made anew on the way back; memory follows OPEN enumerations
    return best, seen + work[0]


def pack_histogram(counts: dict[int, int], capacity: int = CAPACITY, nodes: int = NODES) -> Plan:
    """Patterns (lengths in a sequence, number of such sequences) that use every piece once.

    The first incumbent is best fit of all pieces; where it misses the bound, others come of best fit for the pieces above a
    length and the first descent of the search for the rest, for some lengths; the search goes on from the best of them.
    """
    counts = {int(x): int(n) for x, n in counts.items() if n}
    size = lambda plan: sum(t for _, t in plan)
    bound, best, seen = lower_bound(counts, capacity), best_fit_decreasing(counts, capacity), 0
    lengths = sorted(counts)
    for x in lengths[:: max(1, -(-len(lengths) // INCUMBENTS))] if size(best) > bound else ():
        if seen >= nodes * FOR_INCUMBENTS or size(best) <= bound:
            break
        longer = best_fit_decreasing({y: n for y, n in counts.items() if y > x}, capacity)
        rest, more = _search({y: n for y, n in counts.items() if y <= x}, capacity, None, 0, int(nodes * FOR_INCUMBENTS) - seen)
        seen += more
        if rest is not None and size(longer) + size(rest) < size(best):
            best = longer + rest
    best, more = _search(counts, capacity, best, bound, nodes - seen)
    return Plan(best, size(best), bound, seen + more)




def places(plan: Plan) -> tuple[np.ndarray, ...]:
    """Intervals of piece numbers: (length, first number, first sequence, offset), sorted by length and first number."""
    rows, at, seq = [], {}, 0
    for parts, times in plan.patterns:
        offset = 0
        for x in parts:
            rows.append((x, at.get(x, 0), seq, offset))
            at[x] = at.get(x, 0) + times
            offset += x
        seq += times
    table = np.array(sorted(rows), dtype=np.int64).reshape(-1, 4)
    return tuple(table[:, i].copy() for i in range(4))


def _tokenise(path: str, capacity: int, eos: int, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, end = tokenizer(path, ByteLevelTokenizer), int(eos).to_bytes(4, "little")
        for batch in batches:
            ids_of, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in in_slices(texts):
                out: list[list] = [[], [], [], [], [], []]
                for doc, ids in zip(ids_of[a:b], tok.encode(texts[a:b]), strict=True):
                    ids += end
                    n = len(ids) // 4
                    cut = n % capacity or capacity  # only the first piece may be shorter
                    bounds = [0, *range(min(cut, n), n + 1, capacity)]
                    for piece, (s, e) in enumerate(zip(bounds, bounds[1:], strict=False)):
                        own = ids[4 * s : 4 * e]
                        for column, value in zip(out, (doc, piece, s, e - s, crc(own), own), strict=True):
                            column.append(value)
                arrays = [pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()), strict=True)]
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
                yield pa.RecordBatch.from_arrays(arrays[: 5 + with_ids], names[: 5 + with_ids])

    return run


def _place(table: tuple[np.ndarray, ...], names: list[str]):
    length, first, seq, offset = table
    key = length << 44 | first

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, rank = batch.column("length").to_numpy(), batch.column("_rank").to_numpy()
            at = np.searchsorted(key, n << 44 | rank, side="right") - 1
            columns = [batch.column(c) for c in names]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(seq[at] + rank - first[at], pa.int64()), pa.array(offset[at], pa.int64())], [*names, "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, eos: int = EOS, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32[, ids], sequence_id, offset."""
    ship(docs.sparkSession)
    schema = PIECES + ", ids binary" * with_ids
    read = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(text_col).alias("text"))
    cut = written(read.mapInArrow(_tokenise(tokenizer_path, capacity, eos, with_ids), schema), "pieces")
    counts = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most capacity rows
    table = places(pack_histogram(counts, capacity))
    salts = max(1, min(4096, -(-sum(counts.values()) // RANKED)))
    salted = cut.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)))
    group = Window.partitionBy("length", "_salt")
    ranked = salted.withColumn("_rank", F.row_number().over(group.orderBy("doc_id", "piece")))
    before = salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n"))
    before = before.select("length", "_salt", (F.sum("_n").over(Window.partitionBy("length").orderBy("_salt")) - F.col("_n")).alias("_before"))
    numbered = ranked.join(before, ["length", "_salt"]).withColumn("_rank", (F.col("_rank") - 1 + F.col("_before")).cast("long"))
    names = cut.columns
    return numbered.select(*names, "_rank").mapInArrow(_place(table, names), schema + ", sequence_id long, offset long")
