"""SentencePiece encoding and decoding as a relational lattice.

Texts are cut into units where no piece holds both neighbouring characters: no edge of any lattice crosses such a place, so
units are encoded apart and the cut changes no id.  All distinct units of the corpus go one way:

* their substrings, up to the longest piece, are exploded and equi-joined to the piece table; the hits are the edges;
* the edges are grouped by unit and folded with ``aggregate``, either by ``viterbi`` (unigram models: the path with the
  greatest sum of scores) or by ``merge`` (byte-pair models, whose encoding is not the best path: the best-scored pair
  of neighbours, leftmost on ties, is merged until none is left);
* the units lie bucketed by hash, so that they are shuffled once for group and join alike; the ids go back to the splits
  that hold them, packed into one dictionary for each input split; a task that encodes a split reads that split's dictionary alone.

Nothing is broadcast but the piece table, no list grows with the corpus, and texts are never shuffled.  Units are told apart
by 64-bit hashes.  A unit of more than ``LONG`` characters (a long run that pieces bridge throughout) is folded in place, as a
fold in one row takes the square of its length.

Defined results: a null or empty text has no pieces; a character that no piece covers becomes its UTF-8 bytes' pieces, or
the unknown piece if the model has none; decoding gives back every text but for U+2581, which becomes a space; rows with
equal or null keys are encoded each; other columns are never read, so their names cannot clash.
"""

from __future__ import annotations

import hashlib
import heapq
import math
import struct
import uuid
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import pyarrow.fs
import zstandard
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import drop_path, fresh_path, materialise, release_memory
from .warc import file_system
from .wordbytes import _R, _R_INV, _power, mix

SPACE = "▁"
LONG = 512
SPAN = 4096  # an edge's key is start * SPAN + length
SEEN = 1 << 20  # units that a task remembers, to leave out those it has listed
SLICE = 1 << 20  # characters that are hashed at once, about
RUN = 1 << 18  # bytes of texts that are cut at once, about


@dataclass
class PieceTable:
    pieces: dict[str, tuple[int, float]]  # id and score
    names: list[str]
    bytes: dict[int, int]  # id of each byte's piece
    unknown: int
    longest: int

    @classmethod
    def load(cls, path: str) -> PieceTable:
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        names = [m.id_to_piece(i) for i in range(m.vocab_size())]
        raw = {int(names[i][3:5], 16): i for i in range(len(names)) if m.is_byte(i)}
        plain = {n: (i, m.get_score(i)) for i, n in enumerate(names) if not (m.is_byte(i) or m.is_control(i) or m.is_unknown(i) or m.is_unused(i))}
        return cls.of(plain, names, raw, m.unk_id())

    @classmethod
    def of(cls, pieces: dict[str, tuple[int, float]], names: list[str], raw: dict[int, int] | None = None, unknown: int = 0) -> PieceTable:
        longest = max(map(len, pieces), default=1)
        if longest >= SPAN:
            raise ValueError(f"a piece has {SPAN} characters or more")
        return cls(pieces, names, raw or {}, unknown, longest)

    def uncovered(self, char: str) -> list[int]:
        if not self.bytes:
            return [self.unknown]
        return [self.bytes[b] for b in char.encode("utf-8", "surrogatepass")]

    def frame(self, spark: SparkSession) -> DataFrame:
        """The piece table, and an empty piece that every unit hits once: as large as the vocabulary."""
        rows = [(p, i, s) for p, (i, s) in self.pieces.items() if p]
        return spark.createDataFrame([("", None, None), *rows], "piece string, id int, score double")


# Cutting texts into units.
def units_of(text: str, table: PieceTable) -> list[str]:
    """The units of one text: a leading space is added, and spaces become U+2581."""
    run = Cutter(table).cut([text])
    return [run.text[s:e] for s, e in zip(run.start.tolist(), run.end.tolist())]


@dataclass
class Run:
    text: str  # all texts of the run, spaces as U+2581
    start: np.ndarray  # of each unit
    end: np.ndarray
    hash: np.ndarray  # of each unit, signed
    first: np.ndarray  # index of each text's first unit; one more at the end


class Cutter:
    """Cuts where no piece bridges two characters."""

    def __init__(self, table: PieceTable):
        bridges = {p[i : i + 2] for p in table.pieces for i in range(len(p) - 1)}
        chars = sorted({c for b in bridges for c in b})
        self.kinds = len(chars) + 1  # 0: characters that no longer piece holds
        self.kind = np.zeros(0x110000, np.int32)
        self.kind[[ord(c) for c in chars]] = np.arange(1, self.kinds)
        self.bridged = np.zeros(self.kinds**2, bool)
        for a, b in bridges:
            self.bridged[self.kind[ord(a)] * self.kinds + self.kind[ord(b)]] = True

    def cut(self, texts: list[str | None]) -> Run:
        parts = [SPACE + t.replace(" ", SPACE) if t else "" for t in texts]
        text = "".join(parts)
        begin = np.zeros(len(parts) + 1, np.int64)
        np.cumsum([len(p) for p in parts], out=begin[1:])
        code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        kind = self.kind[code]
        head = np.ones(len(code), bool)
        head[1:] = ~self.bridged[kind[:-1] * self.kinds + kind[1:]]
        head[begin[:-1][np.diff(begin) > 0]] = True
        start = np.flatnonzero(head)
        end = np.append(start[1:], len(code)) if len(start) else start
        return Run(text, start, end, _hashes(code, start, end), np.searchsorted(start, begin))


def _hashes(code: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    out, lo = np.empty(len(start), np.uint64), 0
    while lo < len(start):
        hi = max(lo + 1, int(np.searchsorted(end, start[lo] + SLICE, "right")))
        a, b = int(start[lo]), int(end[hi - 1])
        total = np.zeros(b - a + 1, np.uint64)
        np.cumsum(mix(code[a:b].astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15)) * _power(_R, "up", b - a), out=total[1:])
        s, e = start[lo:hi] - a, end[lo:hi] - a
        out[lo:hi] = mix((total[e] - total[s]) * _power(_R_INV, "down", b - a + 1)[s] + (e - s).astype(np.uint64))
        lo = hi
    return out.view(np.int64)


# Lattices and folds, in tables.
def edges(distinct: DataFrame, table: PieceTable) -> DataFrame:
    """``u``, ``unit`` and its lattice ``edges``: an array of key (start * SPAN + length), score and id.

    ``distinct`` has a row for each unit (``u``, ``unit``).  Rows of a unit stay in one partition from explode to group, so a
    table that is already partitioned by ``u`` is not shuffled.
    """
    starts = distinct.withColumn("s", F.explode(F.expr("sequence(0, length(unit) - 1)")))
    parts = starts.withColumn("l", F.explode(F.expr(f"sequence(if(s = 0, 0, 1), least({table.longest}, length(unit) - s))"))).withColumn("piece", F.expr("substring(unit, s + 1, l)"))
    hits = parts.join(F.broadcast(table.frame(distinct.sparkSession)), "piece")  # bounded by the vocabulary
    return hits.groupBy("u").agg(F.first("unit").alias("unit"), F.collect_list(F.struct(F.expr(f"s * {SPAN} + l").alias("k"), "score", "id")).alias("edges"))


_PIECES = "map_from_entries(transform(edges, e -> struct(e.k AS k, struct(e.score AS score, e.id AS id) AS v)))"
_ID = "coalesce(try_element_at(m, {k}).id, -1 - ascii(substring(unit, {s} + 1, 1)))"


def merge_fold(lattices: DataFrame) -> DataFrame:
    """``u``, ``unit`` and ``path``: the ids of its pieces; -1 - c where no piece covers the character c.

    What is folded is the list of parts, each with the score of merging it with the next one and its negated place, so that
    the greatest part is the first best merge.  A step merges there and looks up the two scores that change.
    """
    score = f"try_element_at(m, {{s}} * {SPAN} + {{l}}).score"
    first = f"transform(sequence(0, length(unit) - 1), i -> struct({score.format(s='i', l='2')} AS score, -i AS back, i AS s, 1 AS l))"
    both = "(get(acc, p).l + get(acc, p + 1).l)"
    before = f"transform(slice(acc, greatest(p, 1), if(p > 0, 1, 0)), x -> struct({score.format(s='x.s', l=f'(x.l + {both})')} AS score, x.back AS back, x.s AS s, x.l AS l))"
    here = f"struct({score.format(s='get(acc, p).s', l=f'({both} + coalesce(get(acc, p + 2).l, {SPAN}))')} AS score, -p AS back, get(acc, p).s AS s, {both} AS l)"
    after = "transform(slice(acc, p + 3, size(acc)), x -> struct(x.score AS score, x.back + 1 AS back, x.s AS s, x.l AS l))"
    merged = f"concat(slice(acc, 1, greatest(p - 1, 0)), {before}, array({here}), {after})"
    step = f"get(transform(array(array_max(acc)), best -> CASE WHEN best.score IS NULL THEN acc ELSE get(transform(array(-best.back), p -> {merged}), 0) END), 0)"
    folded = lattices.withColumn("m", F.expr(_PIECES)).withColumn("acc", F.expr(f"aggregate(sequence(1, length(unit)), {first}, (acc, i) -> coalesce({step}, acc))"))
    return folded.select("u", "unit", F.expr(f"transform(acc, p -> {_ID.format(k=f'p.s * {SPAN} + p.l', s='p.s')})").alias("path"))


def viterbi_fold(lattices: DataFrame, penalty: float = -1e6) -> DataFrame:
    """The same for the path of the greatest score, the longest last piece on ties; an uncovered character costs ``penalty``."""
    reach = f"""array_max(filter(transform(sequence(1, least(longest, e)), l -> struct(
        get(acc, e - l).total + coalesce(try_element_at(m, (e - l) * {SPAN} + l).score, if(l = 1, {penalty!r}D, NULL)) AS total, l AS l)), x -> x.total IS NOT NULL))"""
    table = lattices.withColumn("m", F.expr(_PIECES)).withColumn("longest", F.expr(f"greatest(1, array_max(transform(edges, e -> e.k % {SPAN})))"))
    best = table.withColumn("best", F.expr(f"aggregate(sequence(1, length(unit)), array(struct(0.0D AS total, 0 AS l)), (acc, e) -> concat(acc, array({reach})))"))
    start = "(b.at - get(best, b.at).l)"
    step = f"CASE WHEN b.at = 0 THEN b ELSE struct({start} AS at, concat(array({_ID.format(k=f'{start} * {SPAN} + get(best, b.at).l', s=start)}), b.path) AS path) END"
    back = f"aggregate(sequence(1, length(unit)), struct(length(unit) AS at, CAST(array() AS ARRAY<INT>) AS path), (b, i) -> {step}).path"
    return best.select("u", "unit", F.expr(back).alias("path"))


FOLDS: dict[str, Callable[[DataFrame], DataFrame]] = {"merge": merge_fold, "viterbi": viterbi_fold}


# The same folds of one unit, for those too long for a row.
def merge_unit(unit: str, table: PieceTable) -> list[int]:
    """In time near its length: pairs wait in a heap."""
    get, n = table.pieces.get, len(unit)
    part: list[str | None] = list(unit)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap: list[tuple[float, int, int, str]] = []

    def offer(i: int) -> None:
        j = after[i]
        if j < n:
            both = part[i] + part[j]  # type: ignore[operator]
            hit = get(both)
            if hit is not None:
                heapq.heappush(heap, (-hit[1], i, j, both))

    for i in range(n - 1):
        offer(i)
    while heap:
        _, i, j, both = heapq.heappop(heap)
        if part[i] is None or part[j] is None or after[i] != j or len(part[i]) + len(part[j]) != len(both):  # type: ignore[arg-type]
            continue
        part[i], part[j] = both, None
        after[i] = after[j]
        if after[i] < n:
            before[after[i]] = i
        if before[i] >= 0:
            offer(before[i])
        offer(i)
    return [x for p in part if p is not None for x in ([table.pieces[p][0]] if p in table.pieces else table.uncovered(p))]


def viterbi_unit(unit: str, table: PieceTable, penalty: float = -1e6) -> list[int]:
    best: list[tuple[float, int]] = [(0.0, 0)]
    for e in range(1, len(unit) + 1):
        options = ((best[e - n][0] + (table.pieces[unit[e - n : e]][1] if unit[e - n : e] in table.pieces else penalty if n == 1 else -math.inf), n) for n in range(1, min(table.longest, e) + 1))
        best.append(max(options))
    out: list[list[int]] = []
    at = len(unit)
    while at:
        p = unit[at - best[at][1] : at]
        out.append([table.pieces[p][0]] if p in table.pieces else table.uncovered(p))
        at -= best[at][1]
    return [x for ids in reversed(out) for x in ids]


UNIT_FOLDS = {"merge": merge_unit, "viterbi": viterbi_unit}


# Dictionaries of splits.
class Dictionary:
    """Ids of the units of one split, found by hash; ``key`` is sorted and unsigned, ``ids`` follow its order."""

    def __init__(self, key: np.ndarray, size: np.ndarray, ids: np.ndarray):
        self.key, self.size, self.ids = key, size, ids
        self.at = np.cumsum(size) - size
        bits = max(8, len(key).bit_length() + 1)
        self.shift = np.uint64(64 - bits)
        self.bucket = np.searchsorted(key, np.arange(1 << bits, dtype=np.uint64) << self.shift)

    @classmethod
    def of(cls, u: np.ndarray, size: np.ndarray, ids: np.ndarray) -> Dictionary:
        """From signed hashes in order: the negative ones, which are the greater as unsigned, go behind."""
        n = int(np.searchsorted(u, 0))
        m = int(size[:n].sum())
        return cls(np.concatenate((u[n:], u[:n])).view(np.uint64), np.concatenate((size[n:], size[:n])), np.concatenate((ids[m:], ids[:m])))

    def find(self, hashes: np.ndarray) -> np.ndarray:
        h, last = hashes.view(np.uint64), len(self.key) - 1
        at = np.minimum(self.bucket[(h >> self.shift).astype(np.int64)], last)
        todo = np.flatnonzero(self.key[at] != h)
        while len(todo):
            at[todo] += 1
            if (at[todo] > last).any() or (self.key[at[todo]] > h[todo]).any():
                raise ValueError("a unit is not in its split's dictionary")
            todo = todo[self.key[at[todo]] != h[todo]]
        return at

    def pack(self) -> bytes:
        """Steps of the keys, sizes and ids, byte by byte of their numbers, as these compress well."""
        steps = np.diff(self.key, prepend=np.uint64(0))
        columns = [steps.view(np.uint8).reshape(-1, 8).T, self.size.astype("<u2").view(np.uint8).reshape(-1, 2).T, self.ids.astype("<i4").view(np.uint8).reshape(-1, 4).T]
        return struct.pack("<qq", len(self.key), len(self.ids)) + zstandard.compress(b"".join(c.tobytes() for c in columns), 3)

    @classmethod
    def unpack(cls, data: bytes) -> Dictionary:
        n, m = struct.unpack("<qq", data[:16])
        raw = np.frombuffer(zstandard.decompress(data[16:], max_output_size=max(1, 10 * n + 4 * m)), np.uint8)
        part = lambda lo, rows, width: np.ascontiguousarray(raw[lo : lo + rows * width].reshape(width, rows).T)
        key = np.cumsum(part(0, n, 8).view(np.uint64).ravel(), dtype=np.uint64)
        return cls(key, part(8 * n, n, 2).view("<u2").ravel().astype(np.int64), part(10 * n, m, 4).view("<i4").ravel())


def _dictionary_path(root: str, split: int) -> str:
    return f"{root}/{split & (1 << 64) - 1:016x}"


def _spelled(ids: np.ndarray, size: np.ndarray, table: PieceTable) -> tuple[np.ndarray, np.ndarray]:
    """Ids and their number by unit, with -1 - c replaced by what stands for the uncovered character c."""
    odd = np.flatnonzero(ids < 0)
    if not len(odd):
        return ids, size
    kinds, which = np.unique(ids[odd], return_inverse=True)
    spelled = [table.uncovered(chr(-1 - c)) for c in kinds.tolist()]
    grown = np.ones(len(ids), np.int64)
    grown[odd] = np.array([len(s) for s in spelled])[which]
    out, ends = np.repeat(ids, grown), np.concatenate(([0], np.cumsum(grown)))
    for i, w in zip(ends[odd].tolist(), which.tolist()):
        out[i : i + len(spelled[w])] = spelled[w]
    return out, np.diff(ends[np.concatenate(([0], np.cumsum(size)))])


def _write_dictionaries(root: str, table: PieceTable):
    """Over rows (split, u, path) sorted by split: one file a split, named by it, so that a repeated task writes the same again."""

    def write(split: int, rows: list[pa.RecordBatch]) -> int:
        whole = pa.Table.from_batches(rows).combine_chunks()
        u = whole.column("u").to_numpy()
        if (u[1:] == u[:-1]).any():  # listed twice by a task that forgot
            whole = whole.filter(pa.array(np.concatenate(([True], u[1:] != u[:-1])))).combine_chunks()
        path = whole.column("path").chunk(0)
        offsets = path.offsets.to_numpy()
        ids, size = _spelled(path.values.to_numpy(zero_copy_only=False).astype(np.int64)[offsets[0] : offsets[-1]], np.diff(offsets).astype(np.int64), table)
        fs, at = file_system(_dictionary_path(root, split))
        fs.create_dir(at.rsplit("/", 1)[0], recursive=True)
        with fs.open_output_stream(new := f"{at}.{uuid.uuid4().hex}", compression=None) as f:
            f.write(Dictionary.of(whole.column("u").to_numpy(), size, ids).pack())
        try:
            fs.move(new, at)
        except OSError:  # a store that does not replace: another run of this task has left the same file
            if fs.get_file_info(at).type != pa.fs.FileType.File:
                raise
        return len(size)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        done: list[tuple[int, int]] = []
        for batch in batches:
            split = batch.column(0).to_numpy()
            edge = [0, *(np.flatnonzero(split[1:] != split[:-1]) + 1).tolist(), len(split)]
            for lo, hi in zip(edge, edge[1:]):
                if lo == hi:
                    continue
                if now is not None and int(split[lo]) != now:
                    done.append((now, write(now, held)))
                    held = []
                now = int(split[lo])
                held.append(batch.slice(lo, hi - lo))
        if held:
            done.append((now, write(now, held)))  # type: ignore[arg-type]
        held = []
        release_memory()
        yield pa.RecordBatch.from_arrays([pa.array([d[k] for d in done], pa.int64()) for k in (0, 1)], names=["split", "units"])

    return run


class Seen:
    """A set of numbers as sorted arrays, each less than half as long as the one before."""

    def __init__(self) -> None:
        self.parts: list[np.ndarray] = []

    @property
    def size(self) -> int:
        return sum(map(len, self.parts))

    def lacks(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for p in self.parts:
            out &= p[np.minimum(np.searchsorted(p, x), len(p) - 1)] != x
        return out

    def add(self, x: np.ndarray) -> None:
        """Sorted numbers that the set lacks."""
        if len(x):
            self.parts.append(x)
        while len(self.parts) > 1 and len(self.parts[-2]) < 2 * len(self.parts[-1]):
            both = np.concatenate((self.parts.pop(), self.parts.pop()))
            both.sort(kind="stable")
            self.parts.append(both)


def _list_units(table: PieceTable):
    """The units of each split, each listed once by a task (or as often as ``SEEN`` makes it forget)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cutter, now, seen = Cutter(table), None, Seen()
        for _, split, texts in _runs(batches, 1):
            if split != now or seen.size > SEEN:
                now, seen = split, Seen()
            r = cutter.cut(texts)
            own, at = np.unique(r.hash, return_index=True)
            fresh = seen.lacks(own) & (r.end[at] - r.start[at] <= LONG)
            own, at = own[fresh], at[fresh]
            seen.add(own)
            units = [r.text[s:e] for s, e in zip(r.start[at].tolist(), r.end[at].tolist())]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), split)), pa.array(own), pa.array(units, pa.string())], names=["split", "u", "unit"])
        release_memory()

    return run


def _runs(batches: Iterator[pa.RecordBatch], text: int) -> Iterator[tuple[pa.RecordBatch, int, list]]:
    """Rows, split and texts of runs of about ``RUN`` bytes; column 0 is the split.  Only a run's texts are Python's."""
    for batch in batches:
        split, size = batch.column(0).to_numpy(), pa.compute.binary_length(batch.column(text)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
        edge = [0, *(np.flatnonzero(split[1:] != split[:-1]) + 1).tolist(), len(split)]
        for a, b in zip(edge, edge[1:]):
            lo = a
            while lo < b:
                hi = lo + max(1, int(np.searchsorted(np.cumsum(size[lo : min(b, lo + RUN)] + 1), RUN, "right")))
                run = batch.slice(lo, hi - lo)
                yield run, int(split[a]), run.column(text).to_pylist()
                lo = hi


def piece_bytes(table: PieceTable) -> list[bytes]:
    """What each id stands for, in UTF-8."""
    out = [n.encode() for n in table.names]
    for b, i in table.bytes.items():
        out[i] = bytes([b])
    return out


class Coder:
    """Encodes and decodes runs of texts, given the dictionary of their units."""

    def __init__(self, table: PieceTable, fold: str):
        self.table, self.fold, self.cutter = table, UNIT_FOLDS[fold], Cutter(table)
        raw = piece_bytes(table)
        self.width = np.array([len(b) for b in raw], np.int64)
        self.place = np.cumsum(self.width) - self.width
        self.raw = np.frombuffer(b"".join(raw), np.uint8)

    def encode(self, texts: list[str | None], known: Dictionary | None) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and where each text's begin (one more at the end)."""
        r = self.cutter.cut(texts)
        long = np.flatnonzero(r.end - r.start > LONG)
        short = np.flatnonzero(r.end - r.start <= LONG)
        size, source = np.zeros(len(r.start), np.int64), np.zeros(len(r.start), np.int64)
        if len(short):
            if known is None:
                raise ValueError("the split has no dictionary")
            at = known.find(r.hash[short])
            size[short], source[short] = known.size[at], known.at[at]
        folded = {i: self.fold(r.text[r.start[i] : r.end[i]], self.table) for i in long.tolist()}
        for i, ids in folded.items():
            size[i] = len(ids)
        ends = np.concatenate(([0], np.cumsum(size)))
        live = size.copy()
        live[long] = 0
        ids = np.empty(int(ends[-1]), np.int32)
        into = np.repeat(ends[:-1] - (np.cumsum(live) - live), live) + np.arange(int(live.sum()))
        if len(short):
            ids[into] = known.ids[np.repeat(source - (np.cumsum(live) - live), live) + np.arange(int(live.sum()))]  # type: ignore[union-attr]
        for i, own in folded.items():
            ids[ends[i] : ends[i + 1]] = own
        return ids, ends[r.first]

    def decode(self, ids: np.ndarray, begin: np.ndarray) -> list[str]:
        """The texts; the leading space goes, and U+2581 becomes a space."""
        width = self.width[ids]
        ends = np.concatenate(([0], np.cumsum(width)))
        raw = self.raw[np.repeat(self.place[ids] - ends[:-1], width) + np.arange(int(ends[-1]))].tobytes()
        cut = ends[begin].tolist()
        texts = (raw[a:b].decode("utf-8", "replace").replace(SPACE, " ") for a, b in zip(cut, cut[1:]))
        return [t[1:] if t[:1] == " " else t for t in texts]


def _with_split(docs: DataFrame, key: str, text: str) -> DataFrame:
    """``_split``, ``_key``, ``_text``; the split names a stretch of an input file that one task reads, in every job alike."""
    wanted = [F.col(key).alias("_key"), F.col(text).alias("_text")]
    split = F.xxhash64("_metadata.file_path", "_metadata.file_block_start").alias("_split")
    try:
        return docs.select(split, *wanted)
    except AnalysisException:  # not read from files: written first
        return materialise(docs.select(*wanted), "lattice-texts").select(split, "_key", "_text")


def fold_units(asks: DataFrame, table: PieceTable, fold: str = "merge") -> DataFrame:
    """``u``, ``path`` of every distinct unit of ``asks`` (``u``, ``unit``); no shuffle if it is dealt by ``u``."""
    distinct = asks.groupBy("u").agg(F.min("unit").alias("unit"))
    return FOLDS[fold](edges(distinct, table)).select("u", "path")


#: What an encoded document can give.
OUTPUTS = {"ids": "array<int>", "decoded": "string", "n_ids": "long", "ids_crc32": "long", "decoded_sha256": "string"}


def encode_documents(docs: DataFrame, model: str | PieceTable, key: str = "doc_id", text: str = "text", fold: str = "merge", outputs: tuple[str, ...] = ("ids", "decoded")) -> DataFrame:
    """``key`` and ``outputs`` of every document: its ids, the text decoded from them, their number, the crc32 of them as
    little-endian unsigned 32-bit numbers, the sha256 of the decoded text.  ``fold`` is the model's kind of encoding."""
    spark = docs.sparkSession
    table = model if isinstance(model, PieceTable) else PieceTable.load(model)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    src = _with_split(docs, key, text)
    asks, root = fresh_path(spark, "lattice-units"), fresh_path(spark, "lattice-dictionaries")
    name = f"lattice_{uuid.uuid4().hex}"
    listed = src.select("_split", "_text").mapInArrow(_list_units(table), "split long, u long, unit string")
    listed.repartition(parts, "u").sortWithinPartitions("u").write.option("path", asks).option("compression", "zstd").bucketBy(parts, "u").sortBy("u").saveAsTable(name)
    try:
        answers = spark.table(name).select("split", "u").join(fold_units(spark.table(name), table, fold).hint("merge"), "u").select("split", "u", "path")
        dealt = answers.repartition(parts, "split").sortWithinPartitions("split", "u")
        materialise(dealt.mapInArrow(_write_dictionaries(root, table), "split long, units long"), "lattice-manifest")
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        drop_path(spark, asks)
    kind = src.schema["_key"].dataType.simpleString()

    def made(ids: np.ndarray, begin: np.ndarray, coder: Coder) -> list[pa.Array]:
        cuts = begin.tolist()
        texts = coder.decode(ids, begin) if any(o.startswith("decoded") for o in outputs) else []
        flat = ids.astype("<u4").tobytes()
        make = {
            "ids": lambda: pa.ListArray.from_arrays(pa.array(begin.astype(np.int32)), pa.array(ids)),
            "decoded": lambda: pa.array(texts, pa.string()),
            "n_ids": lambda: pa.array(np.diff(begin).astype(np.int64)),
            "ids_crc32": lambda: pa.array([zlib.crc32(flat[4 * a : 4 * b]) for a, b in zip(cuts, cuts[1:])], pa.int64()),
            "decoded_sha256": lambda: pa.array([hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in texts], pa.string()),
        }
        return [make[o]() for o in outputs]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, now, known = Coder(table, fold), None, None
        for rows, split, texts in _runs(batches, 2):
            if split != now:
                now, known = split, _read_dictionary(root, split)
            ids, begin = coder.encode(texts, known)
            yield pa.RecordBatch.from_arrays([rows.column(1), *made(ids, begin, coder)], names=["_key", *outputs])
        release_memory()

    return src.mapInArrow(run, ", ".join([f"_key {kind}", *(f"{o} {OUTPUTS[o]}" for o in outputs)])).withColumnRenamed("_key", key)


def _read_dictionary(root: str, split: int) -> Dictionary | None:
    """None for a split without a short unit."""
    fs, at = file_system(_dictionary_path(root, split))
    if fs.get_file_info(at).type != pa.fs.FileType.File:
        return None
    with fs.open_input_stream(at, compression=None) as f:
        return Dictionary.unpack(f.read())


def default_model() -> str:
    return public_tokenizers.path("piece_bpe_32k.model")
