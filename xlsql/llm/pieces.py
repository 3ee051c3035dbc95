"""SentencePiece encoding with spans of the original bytes, and decoding."""

from __future__ import annotations

import hashlib
import heapq
import itertools
import re
import struct
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from sentencepiece import sentencepiece_model_pb2 as model_pb2

from xlsql.session import bound_batches

SPACE = "▁"
UNUSED, USER_DEFINED, BYTE = 5, 4, 6
#: Space marks and the characters up to the next one.
WORDS = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+").findall


def default_model() -> str:
    """Path of the public 32k model; every caller may name another."""
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class CharacterMap:
    """The compiled character map of a model: a double-array trie over UTF-8 bytes, and the replacements it points to."""

    def __init__(self, blob: bytes):
        size = struct.unpack("<I", blob[:4])[0] if blob else 0
        self.units = np.frombuffer(blob, "<u4", size // 4, 4) if size else np.zeros(0, "u4")
        self.replacements = blob[4 + size :]
        self.begins = np.zeros(256, bool)
        for b in range(256) if len(self.units) else ():
            at = self._offset(int(self.units[0])) ^ b
            self.begins[b] = at < len(self.units) and int(self.units[at]) & 0x800000FF == b

    def longest(self, raw: bytes, at: int) -> tuple[int, int]:
        """(length, offset of the replacement) of the longest rule that begins at ``at``; length 0: none."""
        if not len(self.units):
            return 0, 0
        units, node, found = self.units, 0, (0, 0)
        node ^= self._offset(int(units[0]))
        for i in range(at, len(raw)):
            node ^= raw[i]
            unit = int(units[node])
            if unit & 0x800000FF != raw[i]:
                break
            node ^= self._offset(unit)
            if unit >> 8 & 1:
                found = (i + 1 - at, int(units[node]) & 0x7FFFFFFF)
        return found

    @staticmethod
    def _offset(unit: int) -> int:
        return (unit >> 10) << ((unit & 0x200) >> 6)

    def replacement(self, offset: int) -> bytes:
        return self.replacements[offset : self.replacements.index(0, offset)]


#: Code points of Latin scripts, whose pairs have a table of their own; columns of the widest table of words.
LATIN, COLUMNS = 384, np.arange(64)


class Merger:
    """Merges of a BPE model over many words at once: the best pair of each word first, the leftmost of equals, until no pair is a piece."""

    #: Words up to this many characters are merged as rows of one table.
    LONGEST = len(COLUMNS)

    def __init__(self, pieces, byte_ids: dict[int, int], unknown: int):
        self.byte_ids, self.unknown = byte_ids, unknown
        ids = {p.piece: i for i, p in enumerate(pieces) if p.type == 1}
        # characters that only occur within pieces can still be halves of a pair
        every = sorted({c for x in ids for c in x} - set(ids))
        self.symbol = {**{c: i for c, i in ids.items()}, **{c: len(pieces) + k for k, c in enumerate(every)}}
        self.n_pieces, self.size = len(pieces), len(pieces) + len(every)
        self.char = np.full(0x110000, -1, "i4")
        for c, i in self.symbol.items():
            if len(c) == 1:
                self.char[ord(c)] = i
        # equal scores share a rank, so the leftmost of them goes first
        order = {x: k for k, x in enumerate(sorted({pieces[i].score for i in ids.values()}, reverse=True))}
        pairs = {}
        for x, i in ids.items():
            for k in range(1, len(x)):
                if x[:k] in self.symbol and x[k:] in self.symbol:
                    pairs[self.symbol[x[:k]] * self.size + self.symbol[x[k:]]] = (order[pieces[i].score], i)
        self.keys = np.array(sorted(pairs), "i8")
        self.rank = np.array([pairs[k][0] for k in self.keys.tolist()], "i4")
        # which piece a rank makes; -1 where pieces of equal score share it
        makes: dict[int, set[int]] = {}
        for r, i in pairs.values():
            makes.setdefault(r, set()).add(i)
        self.made = np.full(len(order), -1, "i4")
        for r, some in makes.items():
            self.made[r] = next(iter(some)) if len(some) == 1 else -1
        self.pairs = pairs
        self._hash()
        # the space mark has place 1 there, the end of a word place 0; the characters of these numbers are none of the table's
        self.place = np.arange(0x110000, dtype="i4")
        self.place[:2], self.place[ord(SPACE)] = LATIN, 1
        symbol = self.char[:LATIN].copy()
        symbol[1], symbol[0] = self.char[ord(SPACE)], -2
        self.latin = self._look(*np.broadcast_arrays(symbol[:, None], symbol[None, :])).reshape(-1)

    NONE = np.int32(2**31 - 1)
    #: Multipliers of the two hash tables.
    MIX = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)

    def _hash(self) -> None:
        """Put the pairs into two tables so that each lies at its place in one of them: a lookup reads one number of each."""
        bits = len(self.keys).bit_length() + 2
        while True:
            tables, shift = [np.full(1 << bits, -1, "i4") for _ in range(2)], np.uint64(64 - bits)
            places = [(self.keys.astype("u8") * np.uint64(m) >> shift).tolist() for m in self.MIX]
            if all(self._put(i, tables, places) for i in range(len(self.keys))):
                self.tables, self.shift = tables, shift
                return
            bits += 1

    @staticmethod
    def _put(i: int, tables: list[np.ndarray], places: list[list[int]]) -> bool:
        side = 0
        for _ in range(200):
            at = places[side][i]
            i, tables[side][at] = int(tables[side][at]), i
            if i < 0:
                return True
            side = 1 - side if places[side][i] == at else side
        return False

    def _look(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair of symbols; ``NONE`` where it makes no piece."""
        key = left.astype("i8") * self.size + right
        if not len(self.keys):
            return np.full(key.shape, self.NONE)
        h = key.view("u8")
        at = self.tables[0][h * np.uint64(self.MIX[0]) >> self.shift]
        flat, keys = at.reshape(-1), key.reshape(-1)
        other = np.flatnonzero((self.keys[at] != key).reshape(-1))
        flat[other] = self.tables[1][keys[other].view("u8") * np.uint64(self.MIX[1]) >> self.shift]
        return np.where((self.keys[at] == key) & (at >= 0) & (left >= 0) & (right >= 0), self.rank[at], self.NONE)

    def _first(self, table: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Ranks of all neighbours of unmerged words: for characters of Latin scripts from one dense table."""
        if codes.shape[1] and int(codes.max()) < LATIN:
            return self.latin[codes[:, :-1] * LATIN + codes[:, 1:]]
        return self._look(table[:, :-1], table[:, 1:])

    def _rows(self, table: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """The table after all merges (-1: a character of no piece, -2: past the end)."""
        out = np.full(table.shape, -2, "i4")
        owner = np.arange(len(table))
        rank = self._first(table, codes)
        while table.shape[1] > 1:
            row = np.arange(len(table))
            best = rank.argmin(1)
            first = rank[row, best]
            live = first != self.NONE
            if not live.all():
                out[owner[~live], : table.shape[1]] = table[~live]
                table, rank, owner, best, first = table[live], rank[live], owner[live], best[live], first[live]
                if not len(table):
                    return out
            row, width = np.arange(len(table)), table.shape[1]
            made = self.made[first]
            for k in np.flatnonzero(made < 0).tolist():
                made[k] = self.pairs[int(table[k, best[k]]) * self.size + int(table[k, best[k] + 1])][1]
            table[row, best] = made
            # what lies behind the merged pair moves up by one; the pair's own entry goes, those at its sides are looked up again
            behind = COLUMNS[: width - 1] > best[:, None]
            table = np.where(behind, table[:, 1:], table[:, :-1])
            rank = np.where(COLUMNS[: width - 2] >= best[:, None], rank[:, 1:], rank[:, :-1])
            for side in (-1, 0):
                j = best + side
                ok = np.flatnonzero((j >= 0) & (j < width - 2))
                j = j[ok]
                rank[ok, j] = self._look(table[ok, j], table[ok, j + 1])
        out[owner, : table.shape[1]] = table
        return out

    def _long(self, word: str) -> list[int]:
        """Symbols of one word of any length, by a queue of its pairs."""
        codes = self.char[np.frombuffer(word.encode("utf-32-le", "surrogatepass"), "<u4")].tolist()
        after, before, version = list(range(1, len(codes) + 1)), list(range(-1, len(codes) - 1)), [0] * len(codes)
        queue: list[tuple[int, int, int, int, int, int]] = []

        def offer(i: int) -> None:
            j = after[i]
            if i >= 0 and j < len(codes) and codes[i] >= 0 and codes[j] >= 0 and (found := self.pairs.get(codes[i] * self.size + codes[j])):
                heapq.heappush(queue, (found[0], i, j, version[i], version[j], found[1]))

        for i in range(len(codes) - 1):
            offer(i)
        gone = [False] * len(codes)
        while queue:
            _, i, j, a, b, made = heapq.heappop(queue)
            if gone[i] or gone[j] or version[i] != a or version[j] != b:
                continue
            codes[i], gone[j], after[i] = made, True, after[j]
            version[i] += 1
            if after[j] < len(codes):
                before[after[j]] = i
            if before[i] >= 0:
                offer(before[i])
            offer(i)
        return [c for i, c in enumerate(codes) if not gone[i]]

    def __call__(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the pieces of all words one after the other, and the number of each; characters of no piece fall back to their bytes, or to the unknown piece."""
        size = np.fromiter(map(len, words), "i8", len(words))
        counts, found, special = np.zeros(len(words), "i8"), [], {}
        for low, high in itertools.pairwise((0, 4, 6, 8, 10, 12, 16, 24, 32, 48, self.LONGEST)):
            members = np.flatnonzero((size > low) & (size <= high))
            for begin in range(0, len(members), 8192):
                part = members[begin : begin + 8192]
                width = int(size[part].max())
                inside, flat = COLUMNS[:width] < size[part][:, None], np.frombuffer("".join([words[k] for k in part.tolist()]).encode("utf-32-le", "surrogatepass"), "<u4")
                table, codes = np.full((len(part), width), -2, "i4"), np.zeros((len(part), width), "i4")
                table[inside], codes[inside] = self.char[flat], self.place[flat]
                odd = ((table == -1) | (table >= self.n_pieces)).any(1)
                done = self._rows(table, codes)
                for k in np.flatnonzero(odd).tolist():
                    special[int(part[k])] = self._ids(done[k][done[k] != -2].tolist(), words[part[k]])
                plain, done = part[~odd], done[~odd]
                counts[plain] = (done != -2).sum(1)
                found.append((plain, done[done != -2]))
        for k in np.flatnonzero(size > self.LONGEST).tolist():
            special[k] = self._ids(self._long(words[k]), words[k])
        for k, ids in special.items():
            counts[k] = len(ids)
        ends = np.cumsum(counts)
        out = np.zeros(int(ends[-1]) if len(ends) else 0, "i4")
        for plain, flat in found:
            n = counts[plain]
            out[np.arange(len(flat)) + np.repeat(ends[plain] - np.cumsum(n), n)] = flat
        for k, ids in special.items():
            out[ends[k] - len(ids) : ends[k]] = ids
        return out, counts

    def _ids(self, symbols: list[int], word: str) -> list[int]:
        """Symbols as ids: what is no piece becomes bytes or the unknown piece."""
        ids: list[int] = []
        at = 0
        for x in symbols:
            if 0 <= x < self.n_pieces:
                at += self.lengths[x]
                ids.append(x)
                continue
            ids += [self.byte_ids[y] for y in word[at].encode("utf-8", "surrogatepass")] if self.byte_ids else [self.unknown]
            at += 1
        return ids


class Encoder:
    """Encodes and decodes with one model; made in each worker from the model's bytes.

    Ids of BPE models come from the own normaliser and the own merges over words. Words are cut where a character that is no space
    mark meets a space mark: no piece of the model has such a place within it, so no merge crosses one. Models of another type, or with
    symbols of their own, take their ids from the library; spans are projected here for all.
    """

    #: Words whose pieces a worker remembers; longer ones are merged anew each time.
    REMEMBERED, LONGEST_REMEMBERED = 200_000, 32

    def __init__(self, model: bytes):
        proto = model_pb2.ModelProto()
        proto.ParseFromString(model)
        self.library = sentencepiece.SentencePieceProcessor(model_proto=model)
        spec = proto.normalizer_spec
        self.rules = CharacterMap(spec.precompiled_charsmap)
        self.prefix, self.squeeze, self.escape = spec.add_dummy_prefix, spec.remove_extra_whitespaces, spec.escape_whitespaces
        self.suffix = proto.trainer_spec.treat_whitespace_as_suffix
        self.mark = SPACE.encode() if self.escape else b" "
        pieces = proto.pieces
        own = [p.piece for p in pieces if p.type == USER_DEFINED]
        self.own = re.compile("|".join(map(re.escape, sorted(own, key=len, reverse=True))).encode()) if own else None
        self.is_byte = np.array([p.type == BYTE for p in pieces])
        self.unknown = self.library.unk_id()
        self.text_of = [p.piece for p in pieces]
        self.width = np.array([1 if p.type == BYTE else len(p.piece.encode()) for p in pieces])
        self.ascii = np.frombuffer("".join([f"{i},".ljust(10, "\0") for i in range(len(pieces))]).encode(), "u1").reshape(-1, 10)[:, : len(str(len(pieces))) + 1]
        crossing = any(re.search(f"[^{SPACE}]{SPACE}", p.piece) for p in pieces if p.type == 1)
        self.merger = None
        if proto.trainer_spec.model_type == 2 and not own and not any(p.type == UNUSED for p in pieces) and self.escape and not self.suffix and not crossing:
            self.merger = Merger(pieces, {int(p.piece[1:-1], 16): i for i, p in enumerate(pieces) if p.type == BYTE}, self.unknown)
            self.merger.lengths = [len(p.piece) for p in pieces]
        self.forget()

    def forget(self) -> None:
        self.place: dict[str, int] = {}
        self.first, self.count, self.pool, self.used = np.zeros(1024, "i8"), np.zeros(1024, "i8"), np.zeros(4096, "i4"), 0

    def learn(self, words: Iterable[str]) -> None:
        """Merge words that are not remembered, all at once."""
        new = list({w for w in words if w not in self.place})
        if not new:
            return
        if len(self.place) + len(new) > 2 * self.REMEMBERED:
            self.forget()
            new = list(set(words))
        ids, counts = self.merger(new)
        start, total = len(self.place), len(ids)
        while len(self.first) < start + len(new):
            self.first, self.count = np.concatenate([self.first, self.first]), np.concatenate([self.count, self.count])
        while len(self.pool) < self.used + total:
            self.pool = np.concatenate([self.pool, self.pool])
        self.pool[self.used : self.used + total] = ids
        self.first[start : start + len(new)] = self.used + np.cumsum(counts) - counts
        self.count[start : start + len(new)] = counts
        self.place.update(zip(new, range(start, start + len(new))))
        self.used += total

    def joined(self, ids: np.ndarray) -> bytes:
        """Decimal ids joined by commas."""
        rows = self.ascii[ids]
        return rows[rows != 0].tobytes()[:-1]

    def encode_batch(self, texts: list[str | None]) -> Iterator[tuple[tuple[bytes, np.ndarray], np.ndarray]]:
        """Alignment and ids of each text; new words of as many texts as can be remembered are merged together."""
        group, held = [], set()
        for t in texts:
            aligned = self.alignment(t) if t else (b"", np.zeros(1, int))
            words = self.words(aligned[0]) if self.merger else None
            own = {w for w in set(words or ()) if len(w) <= self.LONGEST_REMEMBERED}
            if len(held) + len(own) > self.REMEMBERED:
                yield from self._encode_group(group, held)
                group, held = [], set()
            group.append((t, aligned, words))
            held |= own
        yield from self._encode_group(group, held)

    def _encode_group(self, group: list[tuple], held: set[str]) -> Iterator[tuple[tuple[bytes, np.ndarray], np.ndarray]]:
        # a text of more words than that is alone, and encoded slice by slice
        if len(held) <= self.REMEMBERED:
            self.learn(held)
        for t, aligned, words in group:
            yield aligned, self.encode_words(t, words)

    @staticmethod
    def words(normal: bytes) -> list[str]:
        return WORDS(normal.decode("utf-8", "surrogatepass"))

    def encode_words(self, text: str | None, words: list[str] | None = None) -> np.ndarray:
        """Ids of a whole text, given the words of its normal form if they are known."""
        if not text:
            return np.zeros(0, "i4")
        if self.merger is None:
            return np.array(self.library.encode(text, num_threads=1), "i4")
        words = self.words(self.alignment(text)[0]) if words is None else words
        try:
            return self.whole(self.remembered(words))
        except KeyError:
            pass
        parts = []
        # long texts in slices of words, so that what is remembered stays bounded
        for begin in range(0, len(words), self.REMEMBERED // 2):
            some = words[begin : begin + self.REMEMBERED // 2]
            # words that are too long to remember stand between stretches of others
            cuts = [-1, *(k for k, w in enumerate(some) if len(w) > self.LONGEST_REMEMBERED), len(some)]
            self.learn([w for w in some if len(w) <= self.LONGEST_REMEMBERED])
            for i, j in itertools.pairwise(cuts):
                parts.append(self.remembered(some[i + 1 : j]))
                if j < len(some):
                    parts.append(self.merger([some[j]])[0])
        return self.whole(np.concatenate(parts))

    def remembered(self, words: list[str]) -> np.ndarray:
        """Ids of words that are all remembered."""
        at = np.fromiter(map(self.place.__getitem__, words), "i4", len(words))
        size = self.count[at]
        ends = np.cumsum(size)
        return self.pool[np.arange(ends[-1] if len(ends) else 0) + np.repeat(self.first[at] - ends + size, size)]

    def whole(self, ids: np.ndarray) -> np.ndarray:
        """Ids of a whole text from those of its words."""
        if not self.merger.byte_ids and (ids == self.unknown).any():
            # neighbouring unknown characters are one piece
            ids = ids[~((ids == self.unknown) & np.concatenate([[False], ids[:-1] == self.unknown]))]
        return ids

    def normalize(self, text: str) -> tuple[bytes, list[int]]:
        """Normalised bytes, and for each of them and their end the offset in the original bytes it comes from."""
        raw = text.encode("utf-8", "surrogatepass")
        out, source = bytearray(), []
        if not raw:
            return b"", [0]
        pieces, at = [], 0
        while at < len(raw):
            if self.own and (m := self.own.match(raw, at)):
                step, made = m.end() - at, m.group()
            else:
                step, offset = self.rules.longest(raw, at)
                if step:
                    made = self.rules.replacement(offset)
                else:
                    step = 1 if raw[at] < 0x80 else 2 if raw[at] < 0xE0 else 3 if raw[at] < 0xF0 else 4
                    made = raw[at : at + step]
            pieces.append((at, made))
            at += step
        if self.squeeze:
            while pieces and pieces[0][1].strip(b" ") == b"":
                pieces.pop(0)
            if not pieces:
                return b"", [len(raw)]
        add = lambda piece, at: (out.extend(piece), source.extend([at] * len(piece)))
        if self.prefix and not self.suffix:
            add(self.mark, pieces[0][0])
        blank = self.squeeze
        for at, made in pieces:
            for k in range(len(made)):
                c = made[k : k + 1]
                if c == b" ":
                    if not (self.squeeze and blank):
                        add(self.mark, at)
                    blank = self.squeeze
                else:
                    add(c, at)
                    blank = False
        end = len(raw)
        if self.squeeze:
            while out.endswith(self.mark):
                end = source[len(out) - len(self.mark)]
                del out[-len(self.mark) :], source[-len(self.mark) :]
        if self.prefix and self.suffix:
            add(self.mark, end)
        return bytes(out), [*source, end]

    def encode(self, text: str | None) -> list[int]:
        """Ids; null and empty texts have none."""
        return self.encode_words(text).tolist()

    def alignment(self, text: str) -> tuple[bytes, np.ndarray]:
        """Normalised bytes, and the source of each of them and of their end, as ``normalize`` records it, for whole stretches at once.

        The longest rule of the compiled map is sought at each character whose first byte begins one; what lies between rewritten stretches is
        copied with its characters' own offsets.
        """
        if self.own or self.squeeze or self.suffix:
            normal, source = self.normalize(text)
            return normal, np.array(source)
        data = text.encode("utf-8", "surrogatepass")
        raw = np.frombuffer(data, "u1")
        start = np.maximum.accumulate(np.where(raw & 0xC0 != 0x80, np.arange(len(raw)), 0))
        made, sources, done = [], [], 0
        for at in np.flatnonzero(self.rules.begins[raw] & (raw & 0xC0 != 0x80)).tolist():
            if at < done:
                continue
            step, offset = self.rules.longest(data, at)
            if step:
                new = np.frombuffer(self.rules.replacement(offset), "u1")
                made += [raw[done:at], new]
                sources += [start[done:at], np.full(len(new), at)]
                done = at + step
        made, sources = np.concatenate([*made, raw[done:]]), np.concatenate([*sources, start[done:]])
        blank = made == 32
        if len(self.mark) > 1 and blank.any():
            mark, times = np.frombuffer(self.mark, "u1"), np.where(blank, len(self.mark), 1)
            sources = np.repeat(sources, times)
            wide = np.repeat(made, times)
            first = (np.cumsum(times) - times)[blank]
            for k in range(len(mark)):
                wide[first + k] = mark[k]
            made = wide
        lead = np.frombuffer(self.mark, "u1")[: len(self.mark) * self.prefix]
        return np.concatenate([lead, made]).tobytes(), np.concatenate([np.zeros(len(lead), int), sources, [len(raw)]])

    def span_arrays(self, text: str, ids: list[int] | np.ndarray, aligned: tuple[bytes, np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Begin and end of each piece in the original UTF-8 bytes.

        The pieces are laid over the normalised bytes in turn and projected through the recorded sources. A byte piece covers
        one byte of the normalised text; pieces within one source character all have that character's span.
        """
        normal, source = aligned or self.alignment(text)
        length, at = len(normal), np.asarray(ids)
        width = self.width[at]
        if (at == self.unknown).any():
            width = width.copy()
            ids, done = at.tolist(), 0
            for k, i in enumerate(ids):
                if i == self.unknown:
                    width[k] = self._unknown_width(normal, done, ids, k)
                done += int(width[k])
        ends = np.cumsum(width)
        if len(ends) and ends[-1] != length:
            raise ValueError("pieces do not cover the normalised text")
        begin, end = source[ends - width], source[ends]
        within = (end <= begin) & (ends < length)
        if within.any():
            after = np.searchsorted(source, begin[within], "right")
            end[within] = source[np.minimum(after, length)]
        return begin, end

    def spans(self, text: str | None) -> list[tuple[int, str, int, int]]:
        """(id, piece, begin, end) of each piece."""
        ids = self.encode(text)
        if not ids:
            return []
        begin, end = self.span_arrays(text, ids)
        return [(i, self.text_of[i], int(a), int(b)) for i, a, b in zip(ids, begin, end)]

    def _unknown_width(self, normal: bytes, at: int, ids: list[int], k: int) -> int:
        if k + 1 == len(ids):
            return len(normal) - at
        following = self.text_of[ids[k + 1]].encode() if ids[k + 1] != self.unknown else None
        end = at + 1
        while end < len(normal) and (normal[end] & 0xC0 == 0x80 or following and not normal.startswith(following, end)):
            end += 1
        return end - at

    def decode(self, ids: list[int]) -> str:
        return self.library.decode(ids)


def with_pieces(docs: DataFrame, text: str = "text", out: str = "pieces", model: str | bytes | None = None, fields: tuple[str, ...] = ("ids", "decoded")) -> DataFrame:
    """Add a struct column ``out`` with the wanted ``fields``.

    ids (array<int>), n_tokens, ids_sha256 (of the decimal ids joined by commas), decoded (the library's decode of these ids),
    decoded_sha256, spans (array of struct id, piece, begin, end: offsets in the original UTF-8 bytes), covered_bytes (bytes of the original
    text that the spans cover together, all of them unless normalisation drops some).
    Null and empty texts have no ids and decode to the empty text; texts of any length are encoded whole; rows and other columns
    stay as they are, but a column named as ``out`` is replaced.
    """
    bound_batches(docs.sparkSession)
    blob = model if isinstance(model, bytes) else open(model or default_model(), "rb").read()
    kinds = {"covered_bytes": "long", "ids": "array<int>", "n_tokens": "long", "ids_sha256": "string", "decoded": "string", "decoded_sha256": "string", "spans": "array<struct<id:int,piece:string,begin:int,end:int>>"}

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        encoder = Encoder(blob)
        for batch in batches:
            rows = []
            for t, (aligned, ids) in zip(batch, encoder.encode_batch(list(batch))):
                row = {}
                if "ids" in fields:
                    row["ids"] = ids.tolist()
                if "n_tokens" in fields:
                    row["n_tokens"] = len(ids)
                if "ids_sha256" in fields:
                    row["ids_sha256"] = hashlib.sha256(encoder.joined(ids)).hexdigest()
                if "decoded" in fields or "decoded_sha256" in fields:
                    decoded = encoder.decode(ids.tolist()) if len(ids) else ""
                    row["decoded"] = decoded
                    row["decoded_sha256"] = hashlib.sha256(decoded.encode()).hexdigest()
                if "covered_bytes" in fields:
                    begin, end = encoder.span_arrays(t, ids, aligned) if len(ids) else (np.zeros(1, int), np.zeros(1, int))
                    seen = np.maximum.accumulate(np.concatenate([[0], end[:-1]]))
                    row["covered_bytes"] = int(np.maximum(0, end - np.maximum(begin, seen)).sum())
                if "spans" in fields:
                    row["spans"] = [dict(zip(("id", "piece", "begin", "end"), s)) for s in encoder.spans(t)]
                rows.append([row[f] for f in fields])
            yield pd.DataFrame(rows, columns=list(fields))

    return docs.withColumn(out, F.pandas_udf(run, ", ".join(f"{f} {kinds[f]}" for f in fields))(F.col(text)))
