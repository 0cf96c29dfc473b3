"""Best-fit packing by bin completion.

Documents become token ids (a public vocabulary, then an end id); longer ones are cut into pieces of the sequence length,
of which the first may be shorter. Only the lengths matter for the packing, and there are at most `capacity` of them, so
the whole problem is a histogram: the driver solves it with bin completion and gets a few thousand patterns (a multiset of
lengths that fills one sequence, and how many sequences are filled that way), however many documents there are.

Bin completion: around the largest open length, undominated fillings of the rest are enumerated (largest first); the
fullest are tried first, and a branch is cut when the waste it has collected exceeds what the incumbent's number of
sequences allows. Best-fit decreasing gives the first incumbent, and open branches are finished by it from time to time:
the better of both is the new incumbent. The search stops when the incumbent meets the lower bound.

The search is exact only while its documented effort lasts: LIMIT fillings a node, FILLING_STEPS steps to enumerate them,
EFFORT such steps in all, and at most MAX_OPEN open branches. What ends there can only cost sequences, never pieces: the
branch at hand is then finished by best fit.

Each piece knows its rank among pieces of its length: tasks number their own pieces while tokenizing, and a prefix sum over
(task, length) counts gives the task's first rank. Ranks are dealt to patterns by binary search, so no window runs over a
group of equal lengths and no piece is moved. Tokenized pieces are written to the shared folder, which fixes the numbering.

Defined edge results: a null or empty text is the end id alone; an empty table gives no pieces; repeated rows are packed
each by itself; ids may be null; of the documents only doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import base64
import json
import re
import struct
import zlib
from bisect import bisect_left, bisect_right, insort
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, small, written

CAPACITY = 1024
END_ID = 2
VOCABULARY = "byte_bpe_50k"
#: Limits of the search: fillings that a node branches into, steps to enumerate them, such steps in all, open branches.
LIMIT, FILLING_STEPS, EFFORT, MAX_OPEN = 3, 500, 200_000, 256


# ---------------------------------------------------------------- tokens
def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """Token ids as little-endian unsigned 32-bit bytes.

    Texts of Latin letters, ASCII and newlines go to the rank file of the vocabulary, which gives the same ids several
    times faster; others, where the two libraries' character classes could differ, texts that hold a special token and
    texts with a run of over RUN blanks or over RUN other characters (which the rank file's matcher cannot take) go to the
    tokenizer file.
    """

    RUN = 20_000

    def __init__(self, tokenizer_file: str | None = None, rank_file: str | None = None, special: list[str] | None = None):
        import public_tokenizers
        import tiktoken

        self.tokenizer_file = tokenizer_file or vocabulary_path(VOCABULARY + ".json")
        with open(rank_file or vocabulary_path(VOCABULARY + ".tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.quick = tiktoken.Encoding("words", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self._full = None
        self.special = special_strings(self.tokenizer_file) if special is None else special
        self.other = re.compile(r"[^\x20-\x7e\n\u00a1-\u024f]")
        self.run = re.compile(rf"[ \n]{{{self.RUN}}}|[^ \n]{{{self.RUN}}}")

    @property
    def full(self):
        """The tokenizer file, loaded when a text first needs it."""
        if self._full is None:
            from tokenizers import Tokenizer

            self._full = Tokenizer.from_file(self.tokenizer_file)
        return self._full

    def encode(self, text: str) -> bytes:
        if not text:
            return b""
        if self.other.search(text) or len(text) >= self.RUN and self.run.search(text) or any(s in text for s in self.special):
            ids = self.full.encode(text, add_special_tokens=False).ids
        else:
            ids = self.quick(text)
        return np.array(ids, "<u4").tobytes()


def special_strings(tokenizer_file: str) -> list[str]:
    with open(tokenizer_file, encoding="utf-8") as f:
        return [t["content"] for t in json.load(f).get("added_tokens", ())]


# ---------------------------------------------------------------- the packing problem
def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    """Patterns of best-fit decreasing over a histogram: the pieces, largest first, each go to the fullest sequence that
    still has room. Equal sequences are handled together: one that takes a piece is the fullest for its equals, too, and so
    is filled until none fits."""
    by_room: dict[int, list[tuple[tuple, int]]] = {}  # room -> (chain of (length, times), how many sequences)
    rooms: list[int] = []  # sorted

    def put(room: int, fill: tuple, n: int) -> None:
        if room not in by_room:
            by_room[room] = []
            insort(rooms, room)
        by_room[room].append((fill, n))

    for s in sorted(counts, reverse=True):
        left, made = counts[s], []
        at = bisect_left(rooms, s)
        while left and at < len(rooms):
            room = rooms[at]
            groups, each = by_room[room], room // s
            while left and groups:
                fill, n = groups.pop()
                full = min(n, left // each)
                rest = left - full * each if full < n else 0
                if full:
                    made.append((room - each * s, (fill, (s, each)), full))
                if rest:
                    made.append((room - rest * s, (fill, (s, rest)), 1))
                left -= full * each + rest
                if n - full - bool(rest):
                    groups.append((fill, n - full - bool(rest)))
            if groups:
                at += 1
            else:
                del by_room[room], rooms[at]
        if left:
            each = capacity // s
            if left // each:
                made.append((capacity - each * s, ((), (s, each)), left // each))
            if left % each:
                made.append((capacity - left % each * s, ((), (s, left % each)), 1))
        for m in made:
            put(*m)
    return [({s: n for s, n in _flat(fill)}, times) for groups in by_room.values() for fill, times in groups]


def lower_bound(counts: dict[int, int], capacity: int) -> int:
    """No packing uses fewer sequences: for each threshold t, lengths above capacity - t and those above half each need a
    sequence of their own; the lengths from t to half go where the latter leave room."""
    best = 0
    for t in sorted({0, *(s for s in counts if 2 * s <= capacity), *(capacity - s + 1 for s in counts if 2 * s > capacity and 2 * (capacity - s + 1) <= capacity)}):
        alone = sum(n for s, n in counts.items() if s > capacity - t)
        large = sum(n for s, n in counts.items() if 2 * s > capacity and s <= capacity - t)
        room = large * capacity - sum(s * n for s, n in counts.items() if 2 * s > capacity and s <= capacity - t)
        small = sum(s * n for s, n in counts.items() if 2 * s <= capacity and s >= t)
        best = max(best, alone + large + max(0, -(-(small - room) // capacity)))
    return best


def dominated(open_: int, head: int, room: int, fill: dict[int, int]) -> bool:
    """Whether an open length (a bit of open_) could take the place of some of the filling's lengths (the head excepted)
    that are together no longer than it, and still fit: the lengths set free then fit wherever that length would have
    gone. One of the same length as another changes nothing and does not count."""
    sums, several = 1, 0  # bit x is set if some (two or more) of the lengths add up to x
    for s, n in fill.items():
        for _ in range(n - (s == head)):
            several |= (several << s) | ((sums & ~1) << s)
            sums |= sums << s
    near, wide = sums << 1, 1  # bit x is set if x is 1 to `room` above a sum
    while wide < room:
        more = min(wide, room - wide)
        near |= near << more
        wide += more
    return bool((near if room else 0) & open_ or several & open_)


def completions(left: dict[int, int], capacity: int, limit: int = LIMIT, effort: int = FILLING_STEPS) -> tuple[list[dict[int, int]], int]:
    """Up to `limit` undominated fillings of a sequence around the largest open length, fullest first, and the steps taken.

    They are enumerated largest length first; a branch is left when nothing open fits its room. A perfect filling of one
    length more than the branch holds ends the search when there are `limit` of them; it ends after `effort` steps at the
    latest.
    """
    sizes = sorted(left, reverse=True)
    rising = sizes[::-1]
    head = sizes[0]
    open_ = sum(1 << s for s in sizes)
    found: list[tuple[int, dict[int, int]]] = []
    perfect = steps = 0

    def can_take(s: int, fill: dict[int, int]) -> bool:
        return left.get(s, 0) > fill.get(s, 0)

    def grow(room: int, most: int, fill: dict[int, int]) -> bool:
        """Fills the room with lengths up to `most`; True when the search is to end."""
        nonlocal perfect, steps
        steps += 1
        if can_take(room, fill) and room <= most or not room:
            found.append((0, fill | ({room: fill.get(room, 0) + 1} if room else {})))
            perfect += 1
            return perfect >= limit or steps > effort
        took = False
        for s in reversed(rising[:bisect_right(rising, min(room, most))]):
            if can_take(s, fill):
                took = True
                if grow(room - s, s, fill | {s: fill.get(s, 0) + 1}):
                    return True
                if steps > effort:
                    return True
        if not took and not dominated(open_ & ~sum(1 << s for s, n in fill.items() if left[s] == n), head, room, fill):
            found.append((room, dict(fill)))
        return steps > effort

    grow(capacity - head, head, {head: 1})
    found.sort(key=lambda x: (x[0], len(x[1]), sorted(x[1].items(), reverse=True)))
    out: list[dict[int, int]] = []
    for _, f in found:
        if f not in out:
            out.append(f)
        if len(out) == limit:
            break
    if not out:  # the steps ran out before the first leaf: the largest that fit
        room, fill = capacity - head, {head: 1}
        for s in sizes:
            while s <= room and can_take(s, fill):
                fill[s] = fill.get(s, 0) + 1
                room -= s
        out = [fill]
    return out, steps


def bin_completion(counts: dict[int, int], capacity: int = CAPACITY, effort: int = EFFORT, finish_every: int = 200) -> list[tuple[dict[int, int], int]]:
    """Patterns (filling, times) that use as few sequences as the search finds; `effort` bounds the steps of
    its nodes.

    Waste bound: a branch may waste at most what lies between the total and one sequence fewer than the incumbent uses. A
    perfect filling is applied as often as its lengths allow; a wasteful one once at a time while better ones may follow
    it. Every `finish_every` nodes, and where the effort ends, the branch at hand is finished by best fit.
    """
    counts = {s: n for s, n in counts.items() if n}
    if not counts:
        return []
    if max(counts) > capacity or min(counts) < 1:
        raise ValueError("lengths have to be between 1 and the capacity")
    total = sum(s * n for s, n in counts.items())
    least = max(-(-total // capacity), lower_bound(counts, capacity))
    best = best_fit_decreasing(counts, capacity)
    used = sum(n for _, n in best)
    stack: list[tuple[dict[int, int], dict[int, int], tuple, int, int]] = [(counts, {}, (), 0, 0)]
    asked = nodes = 0
    while stack and asked < effort and used > least:
        left, fill, done, number, waste = stack.pop()
        left = dict(left)
        while True:
            if fill:
                room = capacity - sum(s * n for s, n in fill.items())
                times = min(left[s] // n for s, n in fill.items())
                if room:
                    times = min(times, max(1, ((used - 1) * capacity - total - waste) // (4 * room)))
                for s, n in fill.items():
                    left[s] -= n * times
                    if not left[s]:
                        del left[s]
                done, number, waste = (done, (fill, times)), number + times, waste + room * times
            if not left:
                if number < used:
                    best, used = _flat(done), number
                break
            if waste > (used - 1) * capacity - total:
                break
            if asked >= effort or nodes % finish_every == finish_every - 1:
                rest = best_fit_decreasing(left, capacity)
                if (whole := number + sum(n for _, n in rest)) < used:
                    best, used = _flat(done) + rest, whole
                if asked >= effort or used == least:
                    break
            (fill, *others), steps = completions(left, capacity)
            asked, nodes = asked + steps, nodes + 1
            if others and len(stack) < MAX_OPEN:
                state = dict(left)
                stack += [(state, o, done, number, waste) for o in reversed(others)]
    return best


def _flat(done: tuple) -> list[tuple[dict[int, int], int]]:
    """The patterns of a chain of pairs (what came before, pattern)."""
    out = []
    while done:
        done, last = done
        out.append(last)
    return out[::-1]


class Plan:
    """Where the r-th piece of each length goes: (sequence, offset)."""

    def __init__(self, patterns: list[tuple[dict[int, int], int]]):
        rows: dict[int, list[tuple[int, int, int, int]]] = {}
        ranks: Counter[int] = Counter()
        base = 0
        for fill, times in patterns:
            offset = 0
            for s, n in sorted(fill.items(), reverse=True):
                rows.setdefault(s, []).append((ranks[s], base, n, offset))
                ranks[s] += n * times
                offset += s * n
            base += times
        self.sequences = base
        self.rows = {s: np.array(r, np.int64) for s, r in rows.items()}

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
        order = np.argsort(length, kind="stable")
        sizes, starts = np.unique(length[order], return_index=True)
        for s, which in zip(sizes.tolist(), np.split(order, starts[1:])):
            table = self.rows[s]
            row = table[np.searchsorted(table[:, 0], rank[which], side="right") - 1]
            r = rank[which] - row[:, 0]
            sequence[which] = row[:, 1] + r // row[:, 2]
            offset[which] = row[:, 3] + r % row[:, 2] * s
        return sequence, offset


# ---------------------------------------------------------------- the distributed parts
def pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, tokenizer_file: str | None = None,
           rank_file: str | None = None, keep_ids: bool = False) -> DataFrame:
    """docs (doc_id, text) -> doc_id, piece, start, length, ids_crc32, task, local_rank (the piece's number among the
    pieces of its length in its task), and with keep_ids the ids as little-endian bytes. Write it before use."""
    end = struct.pack("<I", end_id)
    special = special_strings(tokenizer_file or vocabulary_path(VOCABULARY + ".json"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(tokenizer_file, rank_file, special)
        task, ranks = TaskContext.get().partitionId(), [0] * (capacity + 1)
        for b in small(batches):
            rows = []
            ids = b.column(0).to_pylist()
            for k, text in enumerate(b.column(1).to_pylist()):
                data = encoder.encode(text or "") + end
                n = len(data) // 4
                first = n % capacity or min(n, capacity)
                at = piece = 0
                while at < n:
                    length = first if not piece else capacity
                    part = data[4 * at:4 * (at + length)]
                    rows.append((ids[k], piece, at, length, zlib.crc32(part), task, ranks[length], *((part,) if keep_ids else ())))
                    ranks[length] += 1
                    at += length
                    piece += 1
            cols = list(zip(*rows)) or [()] * (7 + keep_ids)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), *([pa.binary()] if keep_ids else [])]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names)

    names = ["doc_id", "piece", "start", "length", "ids_crc32", "task", "local_rank", *(["ids"] if keep_ids else [])]
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, task int, local_rank long" + ", ids binary" * keep_ids
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)


def packed(docs: DataFrame, capacity: int = CAPACITY, **options) -> DataFrame:
    """docs (doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset (and ids with keep_ids)."""
    spark = docs.sparkSession
    table = written(pieces(docs, capacity, **options), "pieces")
    per_task = written(table.groupBy("task", "length").agg(F.count("*").alias("n")), "piece-counts")
    counts = {r["length"]: r["n"] for r in per_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    plan = spark.sparkContext.broadcast(Plan(bin_completion(counts, capacity)))
    # first rank of each (task, length): summed within blocks of tasks, then over the blocks, so that a length found in
    # every task is not one window of all tasks
    block = per_task.withColumn("block", F.floor(F.col("task") / 256))
    sums = block.groupBy("length", "block").agg(F.sum("n").alias("n"))
    run = lambda frame, keys, by: frame.withColumn("before", F.sum("n").over(_before(keys, by)))
    inner = run(block, ["length", "block"], "task").select("task", "length", "block", F.coalesce("before", F.lit(0)).alias("inner"))
    outer = run(sums, ["length"], "block").select(F.col("length").alias("l"), F.col("block").alias("k"), F.coalesce("before", F.lit(0)).alias("outer"))
    first = inner.join(outer, (inner["length"] == outer["l"]) & (inner["block"] == outer["k"])).select(
        F.col("task").alias("t"), F.col("length").alias("l"), (F.col("inner") + F.col("outer")).alias("first"))
    # one row a task: an array by length (at most `capacity` numbers), joined to the task's pieces
    starts = first.groupBy("t").agg(F.map_from_entries(F.collect_list(F.struct("l", "first"))).alias("firsts"))
    starts = written(starts, "first-ranks")
    names = [c for c in table.columns if c not in ("task", "local_rank")]
    joined = table.join(starts, table["task"] == starts["t"]).select(*names, (F.col("local_rank") + F.col("firsts")[F.col("length")]).alias("rank"))

    def run_place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            at = {n: k for k, n in enumerate(b.schema.names)}
            sequence, offset = plan.value.place(b.column(at["length"]).to_numpy(), b.column(at["rank"]).to_numpy())
            yield pa.RecordBatch.from_arrays([*(b.column(at[n]) for n in names), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    kinds = dict(table.dtypes)
    schema = ", ".join(f"{n} {kinds[n]}" for n in names) + ", sequence_id long, offset long"
    return joined.mapInArrow(run_place, schema)


def _before(keys: list[str], by: str):
    from pyspark.sql import Window

    return Window.partitionBy(*keys).orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
