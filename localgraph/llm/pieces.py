"""SentencePiece-style encoding and decoding as a max-plus parallel scan.

The best segmentation of a text maximises the sum of its pieces' scores; ties go to the longer last
piece. Best scores at the last WIDTH positions are all that the rest of a text can depend on, so a chunk
of text is a WIDTH x WIDTH matrix over (max, +). Texts longer than CHUNK characters are cut into
chunks that are rows of their own: one pass makes the matrices and the ids between a chunk's walls, an associative prefix product per text
gives each chunk the scores before it, a second pass gives each chunk's map from the state it is left in
to the state it is entered in, composing these maps backwards gives every chunk its exit state, and a third
pass backtraces each chunk independently. Shorter texts are one chunk. Scores are integers, so the cut
positions cannot change a result.

No piece has the space mark after another character or holds a line end, so such positions (walls) are
crossed by no piece. The distinct segments between walls of a block of texts are encoded together, as arrays
over all segments; only the stretch before a chunk's first wall needs one run per state.

Vocabulary, scores and byte pieces come from the model file at a given path. Characters without a piece
become byte pieces. The score-optimal segmentation is the unigram reading of the model; see the README.

Defined results: null or empty text -> no ids, score 0; decode(encode(text)) is the text, also for texts
that contain the space mark itself (its bytes are encoded). Repeated rows and null ids keep their rows.
Extra columns pass through; ids and piece_score are replaced.
"""

from __future__ import annotations

import re
import struct
from dataclasses import dataclass
from itertools import accumulate, islice

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_blocks, stored, table, tidied

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
CHUNK = 32_768
KEEP_SEGMENTS = 300_000
MAX_PIECES = 1 << 20
MARK = "▁"
_RAW_MARK = "\udc81"
NONE = -(1 << 61)


def _fields(b: bytes):
    i = 0

    def number():
        nonlocal i
        x = shift = 0
        while True:
            c = b[i]
            i += 1
            x |= (c & 127) << shift
            shift += 7
            if c < 128:
                return x

    while i < len(b):
        key = number()
        kind = key & 7
        if kind == 0:
            yield key >> 3, number()
        else:
            n = number() if kind == 2 else 8 if kind == 1 else 4
            yield key >> 3, b[i : i + n]
            i += n


@dataclass
class Vocabulary:
    pieces: list[str]
    scores: list[int]
    kinds: list[int]

    def __post_init__(self):
        if len(self.pieces) > MAX_PIECES:
            raise ValueError(f"more than {MAX_PIECES} pieces")
        self.ids: dict[str, int] = {}
        self.trie: dict = {}
        self.bytes = [0] * 256
        low = 0
        for i, (p, s, k) in enumerate(zip(self.pieces, self.scores, self.kinds, strict=True)):
            if k == 6:
                self.bytes[int(p[1:-1], 16)] = i
            elif k == 1 and MARK in p.lstrip(MARK):
                raise ValueError(f"piece {i} has the space mark inside")
            elif k == 1:
                low = min(low, s)
                self.ids[p] = i
                node = self.trie
                for c in p:
                    node = node.setdefault(c, {})
                node[""] = (s, i)
        self.unknown = low - 10
        self.width = max(map(len, self.ids), default=1)

    @classmethod
    def load(cls, path: str = MODEL) -> Vocabulary:
        """Pieces, integer scores and kinds from a model file (protocol buffer)."""
        with open(path, "rb") as f:
            found = [dict(_fields(v)) for k, v in _fields(f.read()) if k == 1]
        scores = [struct.unpack("<f", d[2])[0] if 2 in d else 0.0 for d in found]
        if any(s != int(s) for s in scores):
            raise ValueError("scores must be integers for exact sums")
        return cls([d[1].decode() for d in found], [int(s) for s in scores], [d.get(3, 1) for d in found])


def normalise(text: str) -> str:
    return text.replace(MARK, _RAW_MARK).replace(" ", MARK)


def plain(marked: str) -> str:
    """The text that `normalise` made this of."""
    return marked.replace(MARK, " ").replace(_RAW_MARK, MARK)


class Numbers(dict):
    """Keys numbered as they are met."""

    def __missing__(self, key):
        self[key] = n = len(self)
        return n


class Encoder:
    """Best segmentations, of many short segments at once (arrays) or of one string (loops)."""

    def __init__(self, v: Vocabulary):
        self.v, self.width = v, v.width
        self.forget()
        wall = "" if any("\n" in p for p in v.ids) else "\n"
        self.cut = re.compile(f"{wall and wall + '|'}{MARK}+[^{MARK}{wall}]*|[^{MARK}{wall}]+")
        self.walls = re.compile(f"(?<=[^{MARK}]){MARK}" + (f"|{wall}|(?<={wall})[^{wall}]" if wall else ""))
        inner = sorted({c for p in v.ids for c in p[1:]})
        self.kind = np.zeros(0x110000, np.int16)
        self.kind[[ord(c) for c in inner]] = np.arange(1, len(inner) + 1)
        self.first = np.full(0x110000, -1, np.int32)
        queue, rows = [(v.trie, -1, "")], []
        score, ident, row = [], [], []
        links: list[tuple[int, int, int]] = []
        for node, parent, c in queue:
            if c:
                me = len(score)
                hit = node.get("")
                score.append(hit[0] if hit else NONE)
                ident.append(hit[1] if hit else -1)
                row.append(-1)
                if parent < 0:
                    self.first[ord(c)] = me
                else:
                    if row[parent] < 0:
                        row[parent] = len(rows)
                        rows.append(parent)
                    links.append((row[parent], int(self.kind[ord(c)]), me))
            else:
                me = -1
            queue.extend((child, me, x) for x, child in node.items() if x)
        self.score, self.ident = np.array(score or [NONE], np.int64), np.array(ident or [-1], np.int32)
        self.row = np.array(row or [-1], np.int32)
        self.step = np.full((len(rows) + 1, len(inner) + 1), -1, np.int32)
        if links:
            a, b, c = np.array(links).T
            self.step[a, b] = c
        raw = [bytes([int(p[1:-1], 16)]) if k == 6 else p.replace(MARK, " ").encode() for p, k in zip(v.pieces, v.kinds, strict=True)]
        self.piece_len = np.array([len(r) for r in raw] or [0], np.int64)
        self.piece_at = np.cumsum(self.piece_len) - self.piece_len
        self.piece_bytes = np.frombuffer(b"".join(raw) or b"\0", np.uint8)

    # ---- one string ---------------------------------------------------------------------------

    def matches(self, s: str, start: int, low: int):
        """(end, score, id) of the pieces at start that end after low; id -1: a character without a piece."""
        node, end, single = self.v.trie, start, False
        for c in s[start : start + self.width]:
            node = node.get(c)
            if node is None:
                break
            end += 1
            if (hit := node.get("")) is not None:
                single |= end == start + 1
                if end > low:
                    yield end, *hit
        if not single and start + 1 > low and start < len(s):
            yield start + 1, self.v.unknown, -1

    def forward(self, s: str, entry: dict[int, int], low: int):
        """Best scores and back pointers of s for positions after low, from the entry scores."""
        best, back = [NONE] * (len(s) + 1), [None] * (len(s) + 1)
        for at, score in entry.items():
            best[at] = score
        for start in range(min(entry, default=len(s)), len(s)):
            if (base := best[start]) <= NONE:
                continue
            for end, score, i in self.matches(s, start, low):
                if base + score > best[end]:
                    best[end] = base + score
                    back[end] = (start, i)
        return best, back

    def trace(self, s: str, back, end: int, low: int) -> tuple[list[int], int]:
        """Ids of the pieces on the best path into end that end after low, and where the first begins."""
        out: list[int] = []
        while end > low:
            start, i = back[end]
            if i < 0:
                raw = MARK if s[start] == _RAW_MARK else s[start]
                out.extend(self.v.bytes[b] for b in reversed(raw.encode()))
            else:
                out.append(i)
            end = start
        return out[::-1], end

    # ---- many segments ------------------------------------------------------------------------

    def _group(self, segs: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids of all segments, ids per segment, score per segment) for segments of similar length."""
        lens = np.array([len(s) for s in segs])
        n, top = len(segs), int(lens.max())
        cps = np.frombuffer("".join([s.ljust(top, "\0") for s in segs]).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(n, top)
        kinds = self.kind[cps]
        best = np.full((n, top + 1), NONE, np.int64)
        best[:, 0] = 0
        start, ident = np.zeros((n, top + 1), np.int16), np.full((n, top + 1), -1, np.int32)
        for p in range(top):
            rows = np.flatnonzero(lens > p)
            node, base = self.first[cps[rows, p]], best[rows, p]
            none = (node < 0) | (self.score[node] <= NONE)
            odd = rows[none & (base + self.v.unknown > best[rows, p + 1])]
            best[odd, p + 1], start[odd, p + 1], ident[odd, p + 1] = best[odd, p] + self.v.unknown, p, -1
            for size in range(1, self.width + 1):
                live = node >= 0
                rows, node, base = rows[live], node[live], base[live]
                if not len(rows):
                    break
                gain, end = self.score[node], p + size
                better = (gain > NONE) & (base + gain > best[rows, end])
                hit = rows[better]
                best[hit, end], start[hit, end], ident[hit, end] = (base + gain)[better], p, self.ident[node[better]]
                on = (lens[rows] > end) & (self.row[node] >= 0)
                rows, node, base = rows[on], node[on], base[on]
                if not len(rows):
                    break
                node = self.step[self.row[node], kinds[rows, end]]
        at, path, count = lens.copy(), np.zeros((n, top), np.int32), np.zeros(n, np.int64)
        rows = np.arange(n)
        while len(rows):
            ends = at[rows]
            got = ident[rows, ends]
            path[rows, count[rows]] = np.where(got < 0, -1 - cps[rows, ends - 1].astype(np.int64), got)
            count[rows] += 1
            at[rows] = start[rows, ends]
            rows = rows[at[rows] > 0]
        own = np.repeat(np.arange(n), count)
        nth = np.arange(len(own)) - np.repeat(np.cumsum(count) - count, count)
        flat = path[own, count[own] - 1 - nth]
        if (odd := np.flatnonzero(flat < 0)).size:
            raws = {c: (MARK if chr(-1 - c) == _RAW_MARK else chr(-1 - c)).encode() for c in np.unique(flat[odd]).tolist()}
            width = np.ones(len(flat), np.int64)
            width[odd] = [len(raws[c]) for c in flat[odd].tolist()]
            at = np.cumsum(width) - width
            wide = np.repeat(flat, width)
            for k in range(4):
                more = odd[width[odd] > k]
                wide[at[more] + k] = [self.v.bytes[raws[c][k]] for c in flat[more].tolist()]
            count = np.bincount(own, weights=width, minlength=n).astype(np.int64)
            flat = wide
        return flat, count, best[np.arange(n), lens]

    def segments(self, segs: list[str]):
        """(pool of ids, first, count, score) for distinct segments."""
        first, count, score = (np.zeros(len(segs), np.int64) for _ in range(3))
        pool, used = [], 0
        lens = np.array([len(s) for s in segs], np.int64)
        for low, high in ((0, 6), (6, 10), (10, 16), (16, 28), (28, 64)):
            for part in np.array_split(w := np.flatnonzero((lens > low) & (lens <= high)), len(w) // 60_000 + 1):
                if len(part):
                    flat, n, best = self._group([segs[i] for i in part])
                    first[part], count[part], score[part] = used + np.cumsum(n) - n, n, best
                    pool.append(flat)
                    used += len(flat)
        for i in np.flatnonzero(lens > 64):
            best, back = self.forward(segs[i], {0: 0}, 0)
            ids = self.trace(segs[i], back, len(segs[i]), 0)[0]
            first[i], count[i], score[i] = used, len(ids), best[-1]
            pool.append(np.array(ids, np.int32))
            used += len(ids)
        return (np.concatenate(pool) if pool else np.zeros(0, np.int32)), first, count, score

    def encode_marked(self, texts: list[str]) -> list[tuple[np.ndarray, int]]:
        """(ids, score) of normalised texts, each beginning at a wall. Segments met before are looked up."""
        if len(self.seen) > KEEP_SEGMENTS:
            self.forget()
        seen, old = self.seen, len(self.seen)
        code = seen.__getitem__
        codes = [np.array(list(map(code, self.cut.findall(t))), np.int64) for t in texts]
        if len(seen) > old:
            pool, first, count, score = self.segments(list(islice(seen, old, None)))
            first += len(self.pool)
            self.pool = np.concatenate([self.pool, pool.astype(np.int32)])
            self.pool_at, self.pool_n, self.pool_score = (np.concatenate(x) for x in ((self.pool_at, first), (self.pool_n, count), (self.pool_score, score)))
        out = []
        for c in codes:
            n = self.pool_n[c]
            where = np.repeat(self.pool_at[c] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            out.append((self.pool[where], int(self.pool_score[c].sum())))
        return out

    def forget(self) -> None:
        self.seen = Numbers()
        self.pool = np.zeros(0, np.int32)
        self.pool_at, self.pool_n, self.pool_score = (np.zeros(0, np.int64) for _ in range(3))

    def encode(self, texts: list[str]) -> list[tuple[np.ndarray, int]]:
        return self.encode_marked([MARK + normalise(t) if t else "" for t in texts])

    def decode(self, ids) -> str:
        ids = np.asarray(ids, np.int64)
        n = self.piece_len[ids]
        where = np.repeat(self.piece_at[ids] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        return self.piece_bytes[where].tobytes().decode("utf-8", "replace")[1:]

    # ---- chunks: s is `low` characters of context, then the chunk --------------------------------

    def parts(self, s: str, low: int) -> tuple[int, int] | None:
        """First and last wall at or after low, if any: positions that no piece crosses."""
        found = [m.start() for m in self.walls.finditer(s, max(low, 1))]
        return (found[0], found[-1]) if found else None

    def split(self, s: str, low: int) -> tuple[str, str | None, str]:
        """(before the first wall, between, from the last wall on); all of a chunk without walls is before, and between is None."""
        cut = self.parts(s, low)
        return (s[: cut[0]], s[cut[0] : cut[1]], s[cut[1] :]) if cut else (s, None, "")

    def matrix(self, head: str, tail: str, low: int, base: int | None) -> np.ndarray:
        """`transfer` of a split chunk, with the score between the walls."""
        k = self.width
        out = np.full((k, k), NONE, np.int64)
        ways = [self.forward(head, {low - i: 0}, low)[0] for i in range(min(k, low + 1))]
        if base is None:
            for i, best in enumerate(ways):
                out[i, : min(k, len(head) + 1)] = best[::-1][:k]
            return out
        ends = self.forward(tail, {0: 0}, 0)[0]
        for i, best in enumerate(ways):
            for j, t in enumerate(ends[::-1][:k]):
                if best[-1] > NONE and t > NONE:
                    out[i, j] = best[-1] + base + t
        return out

    def transfer(self, s: str, low: int) -> np.ndarray:
        """Matrix [i, j]: best score from position low - i to position len(s) - j by pieces that end in the chunk."""
        head, middle, tail = self.split(s, low)
        return self.matrix(head, tail, low, None if middle is None else self.encode_marked([middle])[0][1])

    def entered(self, s: str, low: int, vector: np.ndarray):
        entry = {low - i: int(x) for i, x in enumerate(vector) if x > NONE and low - i >= 0}
        return self.forward(s, entry, low)

    def leaves(self, head: str, tail: str | None, low: int, vector: np.ndarray) -> list[int]:
        """`exits` of a split chunk; tail is None where there are no walls."""
        best, back = self.entered(head, low, vector)
        if tail is not None:
            into = low - self.trace(head, back, len(head), low)[1]
            ends = self.forward(tail, {0: 0}, 0)[0][::-1][: self.width]
            return [into if t > NONE else -1 for t in ends] + [-1] * (self.width - len(ends))
        ends = [len(head) - j for j in range(self.width)]
        return [low - self.trace(head, back, e, low)[1] if e >= 0 and best[e] > NONE else -1 for e in ends]

    def exits(self, s: str, low: int, vector: np.ndarray) -> list[int]:
        """For each exit offset the entry offset of its best path; -1 where there is none."""
        head, middle, tail = self.split(s, low)
        return self.leaves(head, None if middle is None else tail, low, vector)

    def path(self, head: str, between: np.ndarray | None, tail: str, low: int, vector: np.ndarray, leave: int) -> np.ndarray:
        """`chunk_ids` of a split chunk, with the ids between the walls."""
        _, back = self.entered(head, low, vector)
        if between is None:
            return np.array(self.trace(head, back, len(head) - leave, low)[0], np.int32)
        begin = self.trace(head, back, len(head), low)[0]
        end = self.trace(tail, self.forward(tail, {0: 0}, 0)[1], len(tail) - leave, 0)[0]
        return np.concatenate([np.array(begin, np.int32), between, np.array(end, np.int32)])

    def chunk_ids(self, s: str, low: int, vector: np.ndarray, leave: int) -> np.ndarray:
        """Ids of the pieces that end in the chunk, on the path left at offset `leave`."""
        head, middle, tail = self.split(s, low)
        return self.path(head, None if middle is None else self.encode_marked([middle])[0][0], tail, low, vector, leave)


def combine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Product over (max, +); associative."""
    c = (a[:, :, None] + b[None, :, :]).max(1)
    return np.where(c < NONE // 2, NONE, c)


def prefix_vectors(matrices: list[np.ndarray]) -> list[np.ndarray]:
    """Scores on entry to each chunk: prefix products applied to the start of the text."""
    start = np.full((1, len(matrices[0])), NONE, np.int64)
    start[0, 0] = 0
    return [m[0] for m in accumulate(matrices[:-1], combine, initial=start)]


def exit_states(maps: list[list[int]]) -> list[int]:
    """Exit offset of each chunk, from the entry maps composed backwards from the end of the text."""
    out = [0]
    for m in reversed(maps[1:]):
        out.append(m[out[-1]])
    return out[::-1]


_ENCODERS: dict[int, Encoder] = {}


def _shared(spark, v: Vocabulary):
    payload = spark.sparkContext.broadcast((v.pieces, v.scores, v.kinds))
    tag = hash((tuple(v.pieces), tuple(v.scores)))

    def get() -> Encoder:
        if tag not in _ENCODERS:
            _ENCODERS[tag] = Encoder(Vocabulary(*payload.value))
        return _ENCODERS[tag]

    return get


def encode_whole(docs: DataFrame, v: Vocabulary, text: str, verify: bool) -> DataFrame:
    get = _shared(docs.sparkSession, v)

    def run(batches):
        e = get()
        for batch in batches:
            for at, texts in in_blocks(range(len(batch)), batch[text], 1 << 21):
                part = batch.iloc[at[0] : at[-1] + 1].copy()
                got = e.encode(texts)
                part["ids"], part["piece_score"] = [g[0] for g in got], [g[1] for g in got]
                if verify:
                    part["round_trip"] = [e.decode(g[0]) == t for g, t in zip(got, texts, strict=True)]
                yield part
        e.forget()

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInPandas(tidied(run), f"{fields}, ids array<int>, piece_score bigint" + ", round_trip boolean" * verify)


def encode_chunked(texts: DataFrame, v: Vocabulary, chunk: int = CHUNK) -> DataFrame:
    """(k1, k2, text) with distinct keys and long texts -> (k1, k2, ids, piece_score)."""
    get, k = _shared(texts.sparkSession, v), v.width
    marked = texts.select("k1", "k2", F.concat(F.lit(" "), "text").alias("s"))
    cut = marked.select("k1", "k2", "s", F.explode(F.expr(f"sequence(0L, (length(s) - 1) div {chunk})")).alias("at"))
    begin = F.greatest(F.col("at") * chunk - (k - 1), F.lit(0))
    # the first sign is the space mark put before the text
    rows = cut.select("k1", "k2", "at", (F.col("at") * chunk - begin).cast("int").alias("low"), F.substr("s", (begin + 1).cast("int"), (F.col("at") * chunk - begin + chunk).cast("int")).alias("s"))
    rows = stored(rows, "chunks")

    norm = normalise

    def matrices(batches):
        for b in batches:
            e = get()
            got = []
            for s, low in zip(b["s"], b["low"], strict=True):
                head, middle, tail = e.split(norm(s), low)
                ids, base = (None, None) if middle is None else e.encode_marked([middle])[0]
                # stored as text: its own space marks go back to what they were
                got.append((e.matrix(head, tail, low, base).tobytes(), plain(head), None if middle is None else plain(tail), None if ids is None else ids.tobytes()))
            b["m"], b["head"], b["tail"], b["ids"] = zip(*got, strict=True) if got else [()] * 4
            yield b[["k1", "k2", "at", "low", "m", "head", "tail", "ids"]]

    def scan(b: pd.DataFrame) -> pd.DataFrame:
        b = b.sort_values("at", ignore_index=True)
        mats = [np.frombuffer(m, np.int64).reshape(k, k) for m in b["m"]]
        b["vec"] = [x.tobytes() for x in prefix_vectors(mats)]
        end = combine(np.frombuffer(b["vec"].iloc[-1], np.int64).reshape(1, k), mats[-1])[0, 0]
        b["total"] = int(end)
        return b[["k1", "k2", "at", "vec", "total"]]

    # each chunk is encoded once; what lies between its walls is not needed as text again
    mats = stored(rows.mapInPandas(tidied(matrices), "k1 bigint, k2 bigint, at bigint, low int, m binary, head string, tail string, ids binary"), "chunk-ids")
    vecs = mats.select("k1", "k2", "at", "m").groupBy("k1", "k2").applyInPandas(scan, "k1 bigint, k2 bigint, at bigint, vec binary, total bigint")
    ready = stored(mats.drop("m", "ids").join(vecs, ["k1", "k2", "at"]), "chunk-states")

    def maps(batches):
        for b in batches:
            e = get()
            b["map"] = [e.leaves(norm(h), None if t is None else norm(t), low, np.frombuffer(x, np.int64)) for h, t, low, x in zip(b["head"], b["tail"], b["low"], b["vec"], strict=True)]
            yield b[["k1", "k2", "at", "map"]]

    def leave(b: pd.DataFrame) -> pd.DataFrame:
        b = b.sort_values("at", ignore_index=True)
        b["leave"] = exit_states([list(m) for m in b["map"]])
        return b[["k1", "k2", "at", "leave"]]

    out_of = ready.mapInPandas(tidied(maps), "k1 bigint, k2 bigint, at bigint, map array<int>")
    out_of = out_of.groupBy("k1", "k2").applyInPandas(leave, "k1 bigint, k2 bigint, at bigint, leave int")

    def trace(batches):
        for b in batches:
            e = get()
            b["part"] = [
                e.path(norm(h), None if i is None else np.frombuffer(i, np.int32), norm(t or ""), low, np.frombuffer(x, np.int64), j)
                for h, t, i, low, x, j in zip(b["head"], b["tail"], b["ids"], b["low"], b["vec"], b["leave"], strict=True)
            ]
            yield b[["k1", "k2", "at", "total", "part"]]

    last = ready.join(out_of, ["k1", "k2", "at"]).join(mats.select("k1", "k2", "at", "ids"), ["k1", "k2", "at"])
    parts = last.mapInPandas(tidied(trace), "k1 bigint, k2 bigint, at bigint, total bigint, part array<int>")
    whole = parts.groupBy("k1", "k2").agg(F.sort_array(F.collect_list(F.struct("at", "part"))).alias("ps"), F.min("total").alias("piece_score"))
    return whole.select("k1", "k2", F.flatten(F.transform("ps", lambda p: p["part"])).alias("ids"), "piece_score")


def encode(docs: DataFrame, v: Vocabulary, text: str = "text", chunk: int = CHUNK, verify: bool = False) -> DataFrame:
    """docs with ids (array<int>) and piece_score appended; with verify, also whether decoding returns the text."""
    docs = docs.drop("ids", "piece_score", *["round_trip"] * verify)
    short = docs.filter(f"`{text}` is null or length(`{text}`) < {chunk}")
    keys = {"k1": F.xxhash64(text), "k2": F.xxhash64(F.lit(1), text)}
    long = docs.filter(F.length(text) >= chunk).withColumns({"__k1": keys["k1"], "__k2": keys["k2"]})
    texts = long.select(F.col("__k1").alias("k1"), F.col("__k2").alias("k2"), F.col(text).alias("text")).dropDuplicates(["k1", "k2"])
    made = encode_chunked(texts, v, chunk).select(F.col("k1").alias("__k1"), F.col("k2").alias("__k2"), "ids", "piece_score")
    joined = long.join(made, ["__k1", "__k2"]).drop("__k1", "__k2")
    if verify:
        joined = decode(joined, v, "ids", "round_trip").withColumn("round_trip", F.col("round_trip") == F.col(text))
    return encode_whole(short, v, text, verify).unionByName(joined)


def decode(docs: DataFrame, v: Vocabulary, ids: str = "ids", into: str = "decoded") -> DataFrame:
    get = _shared(docs.sparkSession, v)
    docs = docs.drop(into)

    def run(batches):
        for batch in batches:
            e = get()
            batch[into] = [e.decode(x if x is not None else []) for x in batch[ids]]
            yield batch

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInPandas(tidied(run), f"{fields}, `{into}` string")


def op10_pieces(spark, sf_dir: str, model: str = MODEL) -> DataFrame:
    """Per document: number of pieces, score, a digest of the ids, and whether decoding returns the text."""
    v = Vocabulary.load(model)
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return encode(docs, v, verify=True).select(
        "doc_id", F.size("ids").cast("long").alias("n_pieces"), "piece_score", F.xxhash64("ids").alias("ids_hash"), "round_trip"
    )
