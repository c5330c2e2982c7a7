"""Offset-preserving subword encoding and decoding of a compiled sentencepiece model.

The model file is parsed here (wire format only).  Normalisation takes, at each
position, the longest prefix that the compiled character map knows, and records
which source byte each normalised byte came from; pieces merged over the
normalised text are projected through that record to spans of source bytes.

Cases: null text is the empty text; an empty text has no pieces (only the end
id where one is asked for); characters outside the vocabulary fall back to
their bytes, or to the unknown id where the model has no byte pieces.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import struct
from functools import lru_cache
from itertools import accumulate, chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.session import arrow_rows, ship

SPACE = "▁"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
MEMO_ENTRIES = 300_000
#: parts merged side by side, and the longest of them; longer ones are merged by a heap
ROWS, LONGEST = 16384, 64
#: ids as decimals joined by a space, decoded surface, (first, end) source bytes of each piece as packed int32, source bytes
Part = tuple[str, str, bytes, int]


def _varint(b: bytes, i: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = b[i]
        i += 1
        value |= (byte & 0x7F) << shift
        shift += 7
        if byte < 0x80:
            return value, i


def _fields(b: bytes):
    i = 0
    while i < len(b):
        key, i = _varint(b, i)
        kind = key & 7
        if kind == 0:
            value, i = _varint(b, i)
        elif kind == 2:
            n, i = _varint(b, i)
            value, i = b[i : i + n], i + n
        else:
            n = 4 if kind == 5 else 8
            value, i = b[i : i + n], i + n
        yield key >> 3, value


class CharacterMap:
    """The compiled character map: a double-array trie over UTF-8 and a pool of replacements."""

    def __init__(self, blob: bytes):
        size = struct.unpack_from("<I", blob)[0] if blob else 0
        self.units = struct.unpack_from(f"<{size // 4}I", blob, 4) if size else ()
        self.pool = blob[4 + size :]

    def longest(self, data: bytes, at: int) -> tuple[int, bytes] | None:
        """(bytes consumed, replacement) of the longest known prefix at `at`."""
        if not self.units:
            return None
        found, node = None, 0
        unit = self.units[0]
        node ^= (unit >> 10) << ((unit & (1 << 9)) >> 6)
        for i in range(at, len(data)):
            byte = data[i]
            node ^= byte
            if node >= len(self.units):
                break
            unit = self.units[node]
            if unit & ((1 << 31) | 0xFF) != byte:
                break
            node ^= (unit >> 10) << ((unit & (1 << 9)) >> 6)
            if (unit >> 8) & 1:
                found = (i + 1 - at, self.units[node] & ((1 << 31) - 1))
        if found is None:
            return None
        return found[0], self.pool[found[1] : self.pool.index(b"\0", found[1])]


class PieceModel:
    def __init__(self, blob: bytes):
        self.pieces: list[str] = []
        self.scores: list[float] = []
        self.kinds: list[int] = []
        self.end_id, self.unknown_id, self.byte_fallback = 2, 0, False
        charsmap = b""
        self.dummy_prefix, self.squeeze, self.escape = True, True, True
        model_kind = 1
        for tag, value in _fields(blob):
            if tag == 1:
                d = dict(_fields(value))
                self.pieces.append(d.get(1, b"").decode())
                self.scores.append(struct.unpack("<f", d[2])[0] if 2 in d else 0.0)
                self.kinds.append(d.get(3, NORMAL))
            elif tag == 2:
                d = dict(_fields(value))
                model_kind = d.get(3, 1)
                self.byte_fallback = bool(d.get(35, 0))
                self.unknown_id = d.get(40, 0)
                self.end_id = d.get(42, 2)
            elif tag == 3:
                d = dict(_fields(value))
                charsmap = d.get(2, b"")
                self.dummy_prefix = bool(d.get(3, 1))
                self.squeeze = bool(d.get(4, 1))
                self.escape = bool(d.get(5, 1))
        if model_kind != 2:
            raise ValueError("only models of the merge kind are supported")
        self.map = CharacterMap(charsmap)
        self.ids = {p: i for i, p in enumerate(self.pieces) if self.kinds[i] in (NORMAL, USER, UNUSED)}
        self.rank = {p: self.scores[i] for p, i in self.ids.items() if self.kinds[i] != UNUSED or len(p) > 1}
        self.bytes = {int(p[3:5], 16): i for i, p in enumerate(self.pieces) if self.kinds[i] == BYTE}
        self.users = sorted((p for i, p in enumerate(self.pieces) if self.kinds[i] == USER), key=len, reverse=True)
        long = [p for p in self.ids if len(p) > 1]
        blank_inside = any(SPACE in p.lstrip(SPACE) for p in long)
        # no piece spans a line end or an inner blank: a text can be cut there and each part encoded once
        self.cuts = not (blank_inside or self.users or self.map.units or self.squeeze) and self.dummy_prefix and self.escape and not any("\n" in p for p in long)
        self.unused = {p for p, i in self.ids.items() if self.kinds[i] == UNUSED}
        self.memo: dict[str, Part] = {}
        self.pairs = {a + b for p in self.ids for a, b in zip(p, p[1:], strict=False)}
        if self.cuts:
            self._tabulate()

    def _tabulate(self) -> None:
        """Symbols and merges as arrays: a symbol is a piece, or a character that only longer pieces have."""
        names = [p for p in self.ids if p in self.rank or len(p) == 1]
        names += sorted({c for p in names for c in p} - set(names))
        at = {p: i for i, p in enumerate(names)}
        self.symbol_id = np.array([self.ids.get(p, -1) for p in names], np.int64)
        # what may stand in a result as it is; the others are taken apart or fall back
        self.plain = np.array([p in self.ids and self.kinds[self.ids[p]] == NORMAL for p in names])
        self.symbol_size = np.array([len(p) for p in names], np.int32)
        chars = {ord(p): i for p, i in at.items() if len(p) == 1}
        self.char_code = np.array(sorted(chars), np.int64)
        self.char_symbol = np.array([chars[c] for c in sorted(chars)], np.int32)
        merges = sorted((at[p[:i]] * len(names) + at[p[i:]], at[p], self.rank[p]) for p in names if p in self.rank for i in range(1, len(p)) if p[:i] in at and p[i:] in at)
        self.merge_key = np.array([m[0] for m in merges], np.int64)
        self.merge_to = np.array([m[1] for m in merges], np.int32)
        self.merge_score = np.array([m[2] for m in merges], np.float64)
        self.decimal = [str(i) for i in range(len(self.pieces))]

    # ---- normalisation ----

    def aligned(self, text: str) -> tuple[list[str], list[int], int]:
        """Characters that replace those of a text, the source byte each one starts at, and the text's bytes.

        Neither blanks are squeezed nor is a prefix added, so parts cut between two
        characters that no entry of the map spans align as they do in the whole text.
        """
        data = text.encode()
        out: list[str] = []
        source: list[int] = []
        if not (self.users or self.map.units):  # every character stands for itself
            out = list(text.replace(" ", SPACE) if self.escape else text)
            if text.isascii():
                return out, list(range(len(text))), len(text)
            ends = list(accumulate([len(c.encode()) for c in text]))
            return out, [0, *ends[:-1]], ends[-1]
        at = 0

        def put(s: str, where: int) -> None:
            for c in s:
                out.append(c)
                source.append(where)

        while at < len(data):
            user = next((u for u in self.users if data.startswith(u.encode(), at)), None)
            if user:
                used, now = len(user.encode()), user
            elif found := self.map.longest(data, at):
                used, now = found[0], found[1].decode()
            else:
                used = 1
                while at + used < len(data) and data[at + used] & 0xC0 == 0x80:
                    used += 1
                now = data[at : at + used].decode()
            put(now.replace(" ", SPACE) if self.escape else now, at)
            at += used
        return out, source, len(data)

    def normalise(self, text: str) -> tuple[str, list[int]]:
        """Normalised text, and for each of its characters (and the end) the source byte it starts at."""
        out, source, size = self.aligned(text)
        blank = SPACE if self.escape else " "
        if self.squeeze:
            kept = [(c, s) for i, (c, s) in enumerate(zip(out, source, strict=True)) if c != blank or (i and out[i - 1] != blank)]
            while kept and kept[-1][0] == blank:
                kept.pop()
            out, source = [c for c, _ in kept], [s for _, s in kept]
        if self.dummy_prefix and out:
            out.insert(0, blank)
            source.insert(0, source[0])
        return "".join(out), [*source, size]

    # ---- segmentation ----

    def merge(self, text: str) -> list[str]:
        """Pieces of a normalised text: the best-scored adjacent pair first, leftmost on ties."""
        if text in self.rank and len(text) == 1:
            return [text]
        parts: list[str] = []
        if self.users:
            for p in re.split("(" + "|".join(map(re.escape, self.users)) + ")", text):
                parts += [p] if p in self.users else list(p)
        else:
            parts = list(text)
        parts = self._merge_short(parts) if len(parts) <= 24 else self._merge_long(parts)
        return [q for p in parts for q in self._resolve(p)] if self.unused else parts

    def _merge_short(self, parts: list[str]) -> list[str]:
        get, none = self.rank.get, float("-inf")
        score = [get(a + b, none) for a, b in zip(parts, parts[1:], strict=False)]
        while score:
            best = max(score)
            if best == none:
                break
            i = score.index(best)
            parts[i] += parts.pop(i + 1)
            del score[i]
            if i:
                score[i - 1] = get(parts[i - 1] + parts[i], none)
            if i < len(score):
                score[i] = get(parts[i] + parts[i + 1], none)
        return parts

    def _merge_long(self, parts: list[str]) -> list[str]:
        rank, n = self.rank, len(parts)
        ahead, behind = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[float, int, int, str]] = []

        def offer(i: int, j: int) -> None:
            score = rank.get(parts[i] + parts[j])
            if score is not None:
                heap.append((-score, i, j, parts[i] + parts[j]))

        for i in range(n - 1):
            offer(i, i + 1)
        heapq.heapify(heap)
        gone = [False] * n
        while heap:
            _, i, j, both = heapq.heappop(heap)
            if gone[i] or gone[j] or ahead[i] != j or parts[i] + parts[j] != both:
                continue
            parts[i], gone[j] = both, True
            ahead[i] = ahead[j]
            if ahead[j] < n:
                behind[ahead[j]] = i
            size = len(heap)
            if behind[i] >= 0:
                offer(behind[i], i)
            if ahead[i] < n:
                offer(i, ahead[i])
            for x in [heap.pop() for _ in range(len(heap) - size)]:
                heapq.heappush(heap, x)
        return [p for p, g in zip(parts, gone, strict=True) if not g]

    def _resolve(self, piece: str) -> list[str]:
        """Unused pieces fall back to the pieces that they were merged from."""
        if piece not in self.unused or len(piece) == 1:
            return [piece]
        options = [(self.rank[piece[:i]] if i > 1 else 0.0, i) for i in range(1, len(piece)) if (i == 1 or piece[:i] in self.rank) and (len(piece) - i == 1 or piece[i:] in self.rank)]
        if not options:
            return [piece]
        i = max(options)[1]
        return self._resolve(piece[:i]) + self._resolve(piece[i:])

    def piece_ids(self, piece: str) -> list[int]:
        if (i := self.ids.get(piece)) is not None:
            return [i]
        if self.byte_fallback:
            return [self.bytes[b] for b in piece.encode()]
        return [self.unknown_id]

    def encode_spans(self, text: str | None) -> list[tuple[int, int, int]]:
        """(id, first source byte, end source byte) of each piece of a whole text.

        Bytes of one fallen-back character share that character's span.
        """
        normal, source = self.normalise(text or "")
        return self._placed(self.merge(normal), source)

    def _placed(self, pieces: list[str], source: list[int]) -> list[tuple[int, int, int]]:
        out, at = [], 0
        for piece in pieces:
            end = at + len(piece)
            out += [(i, source[at], source[end]) for i in self.piece_ids(piece)]
            at = end
        return out

    def encode(self, text: str | None, end: bool = True) -> list[int]:
        ids = [int(x) for part in self.parts(text or "") if part[0] for x in part[0].split(" ")]
        return [*ids, self.end_id] if end else ids

    def parts(self, text: str) -> list[Part]:
        """Each independent part of a text; where parts can be cut, the first has one byte for the dummy prefix before it."""
        if not text:
            return []
        if not self.cuts:
            got = self.encode_spans(text)
            ids = [i for i, _, _ in got]
            return [(" ".join(map(str, ids)), self.surface(ids), np.array([s[1:] for s in got], "<i4").tobytes(), len(text.encode()))]
        words = self.words(text)
        self.learn(words)
        return list(map(self.memo.__getitem__, words))

    def words(self, text: str) -> list[str]:
        """Source parts of a text that may be cut."""
        if not text:
            return []
        if SPACE in text or "  " in text or text[0] == " " or "\0" in text:
            words = re.findall(f"[ {SPACE}]*[^ {SPACE}\n]+|\n|[ {SPACE}]+", " " + text)
        else:  # a blank starts a new part, and so does what stands on either side of a line end
            words = (" " + text.replace(" ", "\0\0 ").replace("\n", "\0\0\n\0\0")).split("\0\0")
        return list(filter(None, words))

    def learn(self, words: list[str]) -> None:
        """Know all source parts of a list; a memory that is full starts anew with them."""
        memo = self.memo
        missing = {w for w in words if w not in memo}
        if not missing:
            return
        if len(memo) >= MEMO_ENTRIES:
            memo.clear()
            missing = set(words)
        self._learn(sorted(missing, key=len))

    def spans(self, parts: list[Part]) -> np.ndarray:
        """(first, end) source bytes of the pieces of all parts of one text, from the parts' own offsets."""
        if not parts:
            return np.zeros((0, 2), np.int64)
        _, _, offsets, sizes = zip(*parts, strict=True)
        found = np.frombuffer(b"".join(offsets), "<i4").reshape(-1, 2)
        size = np.array(sizes, np.int64)
        found = found + np.repeat(np.cumsum(size) - size, np.fromiter(map(len, offsets), np.int64, len(offsets)) // 8)[:, None]
        # the dummy prefix is before the first source byte and has no bytes of its own
        return np.maximum(found - 1, 0) if self.cuts else found

    def _learn(self, words: list[str]) -> None:
        """Align, merge and remember source parts with the spans of their pieces, many at once, shortest first."""
        lo = 0
        while lo < len(words):
            # parts of about one length share a matrix
            most = max(8, 2 * len(words[lo]))
            hi = lo
            while hi < len(words) and len(words[hi]) <= most and hi - lo < ROWS:
                hi += 1
            if len(words[lo]) > LONGEST:
                hi = lo + 1
                self._learn_one(words[lo])
            else:
                self._learn_rows(words[lo:hi])
            lo = hi

    def _learn_one(self, word: str) -> None:
        out, source, size = self.aligned(word)
        got = self._placed(self.merge("".join(out)), [*source, size])
        ids = [i for i, _, _ in got]
        self.memo[word] = (" ".join(map(str, ids)), self.surface(ids), struct.pack(f"<{2 * len(got)}i", *[x for s in got for x in s[1:]]), size)

    def _learn_rows(self, words: list[str]) -> None:
        """The same for rows of a matrix: in each round every row merges its best pair, leftmost on ties.

        Every character stands for itself here but for the blank, so a character's source
        bytes follow from its code.
        """
        size = np.fromiter(map(len, words), np.int64, len(words))
        code = np.frombuffer("".join(words).encode("utf-32-le"), "<u4").astype(np.int64)
        row = np.repeat(np.arange(len(words)), size)
        first = np.cumsum(size) - size
        col = np.arange(len(code)) - first[row]
        # source byte that each character starts at, and each part's bytes
        width = 1 + (code >= 0x80) + (code >= 0x800) + (code >= 0x10000)
        ahead = np.concatenate([[0], np.cumsum(width)])
        code = np.where(code == 0x20, ord(SPACE), code)
        near = np.minimum(np.searchsorted(self.char_code, code), len(self.char_code) - 1)
        symbol = np.where(self.char_code[near] == code, self.char_symbol[near], -1)
        held = np.full((len(words), int(size.max())), -1, np.int64)
        held[row, col] = symbol
        left = size.copy()
        odd = np.zeros(len(words), bool)  # rows with a character that no piece has
        odd[row[symbol < 0]] = True
        self._merge_rows(held, left, np.flatnonzero(~odd))
        cell = np.arange(held.shape[1])[None, :] < left[:, None]
        cell[odd] = False
        odd[np.nonzero(cell)[0][~self.plain[held[cell]]]] = True
        cell[odd] = False
        got, count = held[cell], np.where(odd, 0, left)
        # ends in characters, then in bytes of the part
        ends = np.cumsum(self.symbol_size[got], dtype=np.int64)
        start = np.cumsum(count) - count
        owner = np.repeat(np.arange(len(words)), count)
        ends = ends - np.concatenate([[0], ends])[start][owner] + first[owner]
        pairs = np.empty((len(got), 2), "<i4")
        pairs[:, 1] = ahead[ends] - ahead[first[owner]]
        pairs[1:, 0] = pairs[:-1, 1]
        pairs[start[count > 0], 0] = 0
        raw = pairs.tobytes()
        text = list(map(self.decimal.__getitem__, self.symbol_id[got].tolist()))
        total = (ahead[first + size] - ahead[first]).tolist()
        memo = self.memo
        for w, lo, n, b in zip(words, start.tolist(), count.tolist(), total, strict=True):
            if n:
                memo[w] = (" ".join(text[lo : lo + n]), w.replace(SPACE, " "), raw[8 * lo : 8 * (lo + n)], b)
        for i in np.flatnonzero(odd).tolist():
            self._learn_one(words[i])

    def _merge_rows(self, held: np.ndarray, left: np.ndarray, rows: np.ndarray) -> None:
        """Merge the given rows of symbols in place; `left` is what each row still has."""
        base = len(self.symbol_size)

        def look(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            key = np.where((a < 0) | (b < 0), -1, a * base + b)
            at = np.minimum(np.searchsorted(self.merge_key, key), len(self.merge_key) - 1)
            hit = self.merge_key[at] == key
            return np.where(hit, self.merge_score[at], -np.inf), np.where(hit, self.merge_to[at], -1)

        if not len(rows) or held.shape[1] < 2 or not len(self.merge_key):
            return
        own = held[rows]
        score, to = look(own[:, :-1], own[:, 1:])
        live = np.arange(len(rows))
        place = np.arange(own.shape[1])[None, :]
        while len(live):
            best = score.argmax(axis=1)
            line = np.arange(len(live))
            go = np.isfinite(score[line, best])
            if not go.all():
                done = live[~go]
                held[rows[done]] = own[~go]
                live, own, score, to, best = live[go], own[go], score[go], to[go], best[go]
                line = np.arange(len(live))
                if not len(live):
                    break
            own[line, best] = to[line, best]
            # what is behind the merged pair moves up by one
            step = np.minimum(place + (place > best[:, None]), own.shape[1] - 1)
            own = np.take_along_axis(own, step, 1)
            left[rows[live]] -= 1
            own[line, left[rows[live]]] = -1
            after = np.minimum(step[:, : score.shape[1]], score.shape[1] - 1)
            score, to = np.take_along_axis(score, after, 1), np.take_along_axis(to, after, 1)
            for at in (best - 1, best):
                ok = np.flatnonzero((at >= 0) & (at < score.shape[1]))
                score[ok, at[ok]], to[ok, at[ok]] = look(own[ok, at[ok]], own[ok, at[ok] + 1])
            score[:, -1] = np.where(own[:, -1] < 0, -np.inf, score[:, -1])

    # ---- decoding ----

    def surface(self, ids: list[int]) -> str:
        """Text of ids, blanks restored, the dummy prefix still there."""
        out: list[str] = []
        held = bytearray()
        for i in ids:
            if self.kinds[i] == BYTE:
                held.append(int(self.pieces[i][3:5], 16))
                continue
            if held:
                out.append(held.decode(errors="replace"))
                held.clear()
            if self.kinds[i] == UNKNOWN:
                out.append(" ⁇ ")
            elif self.kinds[i] != CONTROL:
                out.append(self.pieces[i].replace(SPACE, " "))
        if held:
            out.append(held.decode(errors="replace"))
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        text = self.surface(ids)
        if self.dummy_prefix and text.startswith(" "):
            text = text.lstrip(" ") if self.squeeze else text[1:]
        return text


@lru_cache(maxsize=4)
def model(blob: bytes) -> PieceModel:
    return PieceModel(blob)


def encode_documents(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, with_spans: bool = False) -> DataFrame:
    """Encode every whole text with an end id, and decode the ids again.

    Returns id_col, n_tokens, ids_sha256, decoded_sha256, decoded_bytes, spans_sha256, with_ids the ids, and with_spans
    span_start and span_end, the source bytes of each id but the end id.  Digests of spans are over little-endian int32
    pairs; pieces of every text are placed in its bytes by the recorded alignment, and all columns come from them.
    The model file is read on the driver and travels with the task (half a megabyte).
    """
    spark = docs.sparkSession
    ship(spark)
    arrow_rows(spark, 500)
    with open(model_path, "rb") as f:
        blob = f.read()
    key = docs.schema[id_col]
    lists = [*(["ids"] if with_ids else []), *(["span_start", "span_end"] if with_spans else [])]
    out = pa.schema([("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string()), ("decoded_bytes", pa.int64()), ("spans_sha256", pa.string()), *[(n, pa.list_(pa.int32())) for n in lists]])

    def run(batches):
        m = model(blob)
        tail = str(m.end_id)
        for b in batches:
            cols: list[list] = [[] for _ in out]
            texts = [t or "" for t in b.column("_text").to_pylist()]
            # the parts of all texts of a batch are learned side by side
            words = [m.words(t) for t in texts] if m.cuts else None
            if words:
                m.learn(list(chain.from_iterable(words)))
            for k, text in enumerate(texts):
                parts = list(map(m.memo.__getitem__, words[k])) if words else m.parts(text)
                line = " ".join([p[0] for p in parts])
                line = f"{line} {tail}" if line else tail
                decoded = "".join([p[1] for p in parts])
                if m.dummy_prefix and decoded.startswith(" "):
                    decoded = decoded.lstrip(" ") if m.squeeze else decoded[1:]
                raw = decoded.encode()
                spans = m.spans(parts).astype("<i4")
                row = [line.count(" ") + 1, hashlib.sha256(line.encode()).hexdigest(), hashlib.sha256(raw).hexdigest(), len(raw), hashlib.sha256(spans.tobytes()).hexdigest()]
                if with_ids:
                    row.append([int(x) for x in line.split(" ")])
                if with_spans:
                    row += [spans[:, 0], spans[:, 1]]
                for c, v in zip(cols, row, strict=True):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([b.column("_key"), *(pa.array(c, f.type) for c, f in zip(cols, out, strict=True))], names=["_key", *out.names])

    ddl = f"_key {key.dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string, decoded_bytes long, spans_sha256 string" + "".join(f", {n} array<int>" for n in lists)
    got = docs.select(F.col(id_col).alias("_key"), F.col(text_col).alias("_text")).mapInArrow(run, ddl)
    return got.withColumnRenamed("_key", id_col)
