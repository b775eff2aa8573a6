"""BPE encoding and decoding by tree concatenation, and token counts by a compiled transducer.

Both read a tokenizer file of the public `tokenizers` format (BPE model with an end-of-word suffix, byte-level
symbols, NFC / white space / lower-case normaliser, one splitting pattern) and agree with that library exactly.

Encoding. A piece (what the splitting pattern finds) is encoded on its own. A long piece is halved again and again;
the halves are encoded apart and joined by re-encoding a window around the seam, which grows until its first and
last token are those that the two sides had there already. Tokens next to each other in a BPE encoding are exactly those whose
own concatenation encodes to the same two tokens, so a window that agrees at both ends is right everywhere. Where a window of `widest` symbols
still disagrees (long rows of one character shift as a whole), the seam is left open: the join is kept as symbols, and what is open at the root is
merged once, in time n log n. Halves of a piece are encoded one after the other within a task; parallel are the texts.

Counting. The same fact makes the count a finite-state matter: all that the next symbol can depend on is, for each suffix of what was
read that some token starts with, the token before that suffix and how many tokens lie between. Such a situation is a state; each transition is
annotated with the tokens that it adds (joining two tokens takes some away). States are compiled when first met. A text is cut
into chunks. Behind its first white space a chunk's state map is constant, so it is kept as (open head, count, open tail); a chunk inside a long piece
is a `StateMap` from entry states to exit states and counts. Both compose associatively, in a scan by halves.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import re
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from spanweave.llm.shared import texts

#: Unicode white space as the tokenizer library's patterns have it.
BLANKS = r"\t-\r\x20\x85\xa0  -     　"


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies: printable Latin-1 bytes
    stand for themselves, the others for the characters from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    rest = iter(range(0x100, 0x200))
    return [chr(b) if b in plain else chr(next(rest)) for b in range(256)]


class Tokenizer:
    """Vocabulary, merges and text splitting of one file, and the two encoders."""

    #: Symbols up to which a piece is merged in one go.
    leaf = 64
    #: Symbols up to which the window around a seam grows.
    widest = 256
    #: Pieces remembered; beyond it the memory starts afresh.
    remember = 300_000

    def __init__(self, path: str):
        spec = json.loads(open(path, encoding="utf-8").read())
        model, split = spec["model"], spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        kinds = [n["type"] for n in spec["normalizer"]["normalizers"]]
        if model["type"] != "BPE" or not model["end_of_word_suffix"] or kinds != ["NFC", "Replace", "Lowercase"] or spec["decoder"]:
            raise ValueError(f"{path}: not a tokenizer of the kind that is implemented here")
        vocab, end = model["vocab"], model["end_of_word_suffix"]
        self.names = {i: t for t, i in vocab.items()} | {t["id"]: t["content"] for t in spec["added_tokens"]}
        symbols = byte_symbols()
        self.inner, self.last = [vocab[s] for s in symbols], [vocab[s + end] for s in symbols]
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        self.origin: dict[int, tuple[int, int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            joined = vocab[a + b]
            self.merges[vocab[a], vocab[b]] = rank, joined
            self.origin.setdefault(joined, (vocab[a], vocab[b], rank))
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special = special
        self.special_at = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")") if special else None
        self.pieces_of = regex.compile(split.replace(r"\s", BLANKS)).findall
        self.byte_of = {ord(c): b for b, c in enumerate(symbols)}
        self.path, self._library = path, None
        self._known: dict[str, tuple[int, str, str]] = {}
        self._symbols: dict[int, list[int]] = {}
        self._merged: dict[tuple[int, ...], list[int]] = {}

    def symbols_of(self, token: int) -> list[int]:
        found = self._symbols.get(token)
        if found is None:
            a, b, _ = self.origin.get(token, (token, None, 0))
            found = self._symbols[token] = [token] if b is None else self.symbols_of(a) + self.symbols_of(b)
        return found

    # ---- text to pieces
    def normalise(self, text: str) -> str:
        """White space is only ever a separator for the splitting pattern, so it is left as it is."""
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # lower-cased by itself, not as a word's end
        return text.lower()

    def pieces(self, text: str) -> list[str]:
        """The pieces of an ordinary stretch. Beyond the Latin, Greek and Cyrillic blocks Unicode tables differ by their year:
        there the library's own normaliser and splitter decide."""
        if not _RECENT.search(text):
            return self.pieces_of(self.normalise(text))
        if self._library is None:
            from tokenizers import Tokenizer as Library

            self._library = Library.from_file(self.path)
        found = self._library.pre_tokenizer.pre_tokenize_str(self._library.normalizer.normalize_str(text))
        return [bytes(p.translate(self.byte_of).encode("latin-1")).decode() for p, _ in found]

    def segments(self, text: str) -> Iterator[tuple[str, int | None]]:
        """(text, None) for ordinary stretches, (content, id) for special tokens spelt out in the text."""
        if self.special_at is None or "<" not in text:
            yield text, None
            return
        for part in self.special_at.split(text):
            if part:
                yield part, self.special.get(part)

    # ---- one piece
    def merge(self, ids: list[int]) -> list[int]:
        """Lowest rank first, leftmost first."""
        if len(ids) > self.leaf:
            return self.merge_long(ids)
        ids, merges = list(ids), self.merges
        ranks = [merges.get(p) for p in zip(ids, ids[1:], strict=False)]
        while True:
            best, at = None, -1
            for i, r in enumerate(ranks):
                if r is not None and (best is None or r[0] < best):
                    best, at = r[0], i
            if at < 0:
                return ids
            ids[at : at + 2] = [ranks[at][1]]
            del ranks[at]
            if at:
                ranks[at - 1] = merges.get((ids[at - 1], ids[at]))
            if at < len(ranks):
                ranks[at] = merges.get((ids[at], ids[at + 1]))

    def again(self, ids: list[int]) -> list[int]:
        """`merge`, remembered: leaves and windows of monotonous pieces repeat."""
        key = tuple(ids)
        found = self._merged.get(key)
        if found is None:
            if len(self._merged) >= 20_000:
                self._merged.clear()
            found = self._merged[key] = self.merge(ids)
        return found

    def merge_long(self, ids: list[int]) -> list[int]:
        """The same in time n log n: symbols in a linked list, the places of each rank's pairs in lists, ranks in a heap. A rank is swept
        from left to right unless a lower one turns up meanwhile."""
        token, n, merges = list(ids), len(ids), self.merges
        after, before = [*range(1, n + 1)], [*range(-1, n - 1)]
        places: dict[int, list[int]] = {}
        for i in range(n - 1):
            found = merges.get((token[i], token[i + 1]))
            if found is not None:
                places.setdefault(found[0], []).append(i)
        heap = [*places]
        heapq.heapify(heap)
        while heap:
            rank = heapq.heappop(heap)
            todo = sorted(places.pop(rank))
            for k, i in enumerate(todo):
                j = after[i]
                if token[i] < 0 or j >= n:
                    continue
                found = merges.get((token[i], token[j]))
                if found is None or found[0] != rank:
                    continue
                token[i], token[j] = found[1], -1
                after[i] = end = after[j]
                lower = False
                if end < n:
                    before[end] = i
                for left, right in ((before[i], i), (i, end)):
                    if left >= 0 and right < n and (pair := merges.get((token[left], token[right]))) is not None:
                        if pair[0] not in places:
                            places[pair[0]] = []
                            heapq.heappush(heap, pair[0])
                        places[pair[0]].append(left)
                        lower |= pair[0] < rank
                if lower:
                    if rank in places:
                        places[rank] += todo[k + 1 :]
                    else:
                        places[rank] = todo[k + 1 :]
                        heapq.heappush(heap, rank)
                    break
        return [t for t in token if t >= 0]

    def base(self, piece: str) -> list[int]:
        data = piece.encode()
        return [*(self.inner[b] for b in data[:-1]), self.last[data[-1]]]

    def tree(self, base: list[int]) -> list[int]:
        """Encode base symbols by halves."""
        found, is_open = self.half(base, 0, len(base))
        return self.merge_long(found) if is_open else found

    def half(self, base: list[int], start: int, end: int) -> tuple[list[int], bool]:
        """The encoding of base[start:end], or its symbols and True where a seam inside is left open."""
        if end - start <= self.leaf:
            return self.again(base[start:end]), False
        middle = (start + end) // 2
        (left, open_left), (right, open_right) = self.half(base, start, middle), self.half(base, middle, end)
        joined = None if open_left or open_right else self.join(left, right)
        return (base[start:end], True) if joined is None else (joined, False)

    def join(self, left: list[int], right: list[int]) -> list[int] | None:
        """Both sides as one encoding; None where the widest window does not agree with them."""
        reach = 2
        while True:
            a, b = left[-reach:], right[:reach]
            whole_left, whole_right = len(a) == len(left), len(b) == len(right)
            window = [s for t in a + b for s in self.symbols_of(t)]
            if len(window) > self.widest:
                return None
            seam = self.again(window)
            if (whole_left or seam[0] == a[0]) and (whole_right or seam[-1] == b[-1]) and (len(seam) > 1 or (whole_left and whole_right)):
                return left[: len(left) - len(a)] + seam + right[len(b) :]
            reach *= 2

    def encode_piece(self, piece: str) -> list[int]:
        return self.tree(self.base(piece))

    # ---- whole texts
    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for part, token in self.segments(text):
            if token is not None:
                out.append(token)
            else:
                for piece in self.pieces(part):
                    out += self.encode_piece(piece)
        return out

    def decode(self, ids: list[int]) -> str:
        """Token names joined by blanks: the files have no decoder of their own."""
        return " ".join(map(self.names.__getitem__, ids))

    def rendered(self, piece: str) -> tuple[int, str, str]:
        """(tokens, their ids in decimal, their decoded text), remembered by piece."""
        ids = self.encode_piece(piece)
        if len(self._known) >= self.remember:
            self._known.clear()
        found = self._known[piece] = len(ids), " ".join(map(str, ids)), self.decode(ids)
        return found

    def digest(self, text: str) -> tuple[int, str, str]:
        """(tokens, SHA-256 of the ids in decimal, SHA-256 of the decoded text) of a whole text."""
        total, ids, words = 0, [], []
        for part, token in self.segments(text):
            if token is not None:
                found = [(1, str(token), self.names[token])]
            else:
                known, rendered = self._known.get, self.rendered
                found = [known(p) or rendered(p) for p in self.pieces(part)]
            total += sum(f[0] for f in found)
            ids += [f[1] for f in found]
            words += [f[2] for f in found]
        return total, hashlib.sha256(" ".join(ids).encode()).hexdigest(), hashlib.sha256(" ".join(words).encode()).hexdigest()


class StateMap:
    """What a stretch of symbols does to each entry state: (exit state, tokens added). Filled in for the states that are asked for: the stretch is run from the start
    state once, and any other entry only until its path meets that one, as from there on both are the same. States are given by content, so
    that a machine compiled afresh in between does no harm."""

    #: Steps of the first path that are kept to be met; a path that has not met it by then is run to its end.
    kept = 512

    def __init__(self, machine: CountTransducer, symbols: list[int]):
        self.machine, self.symbols, self.path = machine, symbols, []
        self.known = {_START: self._run(_START)}

    def _run(self, entry: tuple) -> tuple[tuple, int]:
        machine, first, total = self.machine, entry == _START, 0
        state = machine.numbered(entry)
        for i, s in enumerate(self.symbols):
            state, added = machine.moves[state].get(s) or machine.compile_move(state, s)
            total += added
            if i < self.kept:
                now = machine.states[state]
                if first:
                    self.path.append((now, total))
                elif now == self.path[i][0]:
                    end, whole = self.known[_START]
                    return end, total + whole - self.path[i][1]
        return machine.states[state], total

    def __call__(self, entry: tuple) -> tuple[tuple, int]:
        if entry not in self.known:
            self.known[entry] = self._run(entry)
        return self.known[entry]


class Composed:
    """One state map after another: again a state map."""

    def __init__(self, first, second):
        self.first, self.second = first, second
        self.known = {_START: self._run(_START)}

    def _run(self, entry: tuple) -> tuple[tuple, int]:
        between, added = self.first(entry)
        end, more = self.second(between)
        return end, added + more

    __call__ = StateMap.__call__


#: Of a state: for each open start its node in the tree of tokens, the token before it and the tokens since.
_START = ((0, -1, 0),)


class CountTransducer:
    """Token counts of pieces, and of texts by chunks."""

    #: States and pieces remembered; beyond that the machine is compiled afresh.
    most_states, most_pieces = 150_000, 500_000

    def __init__(self, tokenizer: Tokenizer, chunk: int = 16_384):
        self.tokenizer, self.chunk = tokenizer, chunk
        self.child: dict[tuple[int, int], int] = {}
        self.token_at: list[int | None] = [None]
        self.leaf_at: list[bool] = [True]
        singles = [*tokenizer.inner, *tokenizer.last]
        for token in [*singles, *tokenizer.origin]:
            node = 0
            for s in tokenizer.symbols_of(token):
                nxt = self.child.get((node, s))
                if nxt is None:
                    nxt = self.child[node, s] = len(self.token_at)
                    self.token_at.append(None)
                    self.leaf_at.append(True)
                    self.leaf_at[node] = False
                node = nxt
            self.token_at[node] = token
        self._fits: dict[tuple[int, int], bool] = {}
        self._whole: dict[int, bool] = {}
        self._pieces: dict[str, int] = {}
        self._reset()

    def _reset(self) -> None:
        self.number, self.states, self.moves = {_START: 0}, [_START], [{}]

    def numbered(self, state: tuple) -> int:
        """The number of a state, compiled anew if it is not known."""
        at = self.number.get(state)
        if at is None:
            at = self.number[state] = len(self.states)
            self.states.append(state)
            self.moves.append({})
        return at

    def whole(self, token: int) -> bool:
        """Whether a token's own symbols encode to it."""
        known = self._whole.get(token)
        if known is None:
            known = self._whole[token] = self.tokenizer.merge(self.tokenizer.symbols_of(token)) == [token]
        return known

    def fits(self, a: int, b: int) -> bool:
        """Whether tokens a, b next to each other encode to themselves."""
        if a < 0:
            return True
        known = self._fits.get((a, b))
        if known is None:
            if len(self._fits) >= self.most_pieces:
                self._fits.clear()
            known = self._fits[a, b] = self.tokenizer.merge(self.tokenizer.symbols_of(a) + self.tokenizer.symbols_of(b)) == [a, b]
        return known

    def compile_move(self, state: int, symbol: int) -> tuple[int, int]:
        """The state after `symbol` and the tokens that it adds."""
        open_starts, added, token = [], None, None
        for node, before, back in self.states[state]:
            nxt = self.child.get((node, symbol))
            if nxt is None:
                continue
            name = self.token_at[nxt]
            if token is None and name is not None and self.whole(name) and self.fits(before, name):
                token, added = name, back + 1
            if not self.leaf_at[nxt]:
                open_starts.append((nxt, before, back))
        now = (*((n, b, k - added) for n, b, k in open_starts), (0, token, 0))
        at = self.numbered(now)
        self.moves[state][symbol] = at, added
        return at, added

    def piece(self, piece: str) -> int:
        """Tokens of one piece: the sum of the annotations along its path."""
        data, inner = piece.encode(), self.tokenizer.inner
        if len(data) > self.chunk:
            return self.long_piece(data)
        if len(self.states) > self.most_states:
            self._reset()
        state = total = 0
        for b in data[:-1]:
            s = inner[b]
            state, added = self.moves[state].get(s) or self.compile_move(state, s)
            total += added
        s = self.tokenizer.last[data[-1]]
        total += (self.moves[state].get(s) or self.compile_move(state, s))[1]
        if len(self._pieces) >= self.most_pieces:
            self._pieces.clear()
        self._pieces[piece] = total
        return total

    def long_piece(self, data: bytes) -> int:
        """A piece in chunks: their state maps, composed by halves."""
        symbols, maps = [*(self.tokenizer.inner[b] for b in data[:-1]), self.tokenizer.last[data[-1]]], []
        for at in range(0, len(symbols), self.chunk):
            if len(self.states) > self.most_states:
                self._reset()
            maps.append(StateMap(self, symbols[at : at + self.chunk]))
        while len(maps) > 1:
            maps = [Composed(a, b) for a, b in zip(maps[::2], maps[1::2], strict=False)] + maps[len(maps) - len(maps) % 2 :]
        return maps[0](_START)[1]

    def run(self, text: str) -> int:
        known, piece = self._pieces.get, self.piece
        return sum([known(p) or piece(p) for p in self.tokenizer.pieces(text)])

    # ---- chunk maps: (open head, tokens between, open tail); tail None: no white space yet, all is head
    def chunk_map(self, text: str) -> tuple[str, int, str | None]:
        first = _BLANK.search(text)
        if first is None:
            return text, 0, None
        last = max(text.rfind(" "), text.rfind("\n"), first.start())
        return text[: first.start()], self.run(text[first.start() : last + 1]), text[last + 1 :]

    def compose(self, a: tuple, b: tuple) -> tuple:
        if a[2] is None:
            return (a[0] + b[0], b[1], b[2])
        if b[2] is None:
            return (a[0], a[1], a[2] + b[0])
        return (a[0], a[1] + self.run(a[2] + b[0]) + b[1], b[2])

    def count(self, text: str) -> int:
        total = 0
        for part, token in self.tokenizer.segments(text):
            if token is not None:
                total += 1
                continue
            maps = [self.chunk_map(part[i : i + self.chunk]) for i in range(0, len(part), self.chunk)]
            while len(maps) > 1:
                pairs = [self.compose(a, b) for a, b in zip(maps[::2], maps[1::2], strict=False)]
                maps = pairs + maps[len(maps) - len(maps) % 2 :]
            for head, between, tail in maps:
                total += self.run(head) + between + (self.run(tail) if tail else 0)
        return total


#: Where a chunk may be opened: these never join with what stands before or after them.
_BLANK = re.compile("[ \n]")
#: Scripts from Armenian on, general punctuation and Latin additions apart.
_RECENT = re.compile("[\u0500-\u1dff\u2080-\u20ff\u2c00-\uffff\U00010000-\U0010ffff]")


@lru_cache(maxsize=2)
def tokenizer_of(path: str) -> Tokenizer:
    return Tokenizer(path)


@lru_cache(maxsize=2)
def transducer_of(path: str) -> CountTransducer:
    return CountTransducer(tokenizer_of(path))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, list]]:
    for batch in batches:
        for at in range(0, batch.num_rows, 512):
            part = batch.slice(at, 512)
            yield part.column(0), part.column(1).to_pylist()


def encode_texts(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, ids (the token ids), decoded (their text). A null or empty text has no ids; repeated rows and ids are encoded row by row, an empty table gives no rows,
    and other columns are ignored. A text's tokens are held in one row: for texts of hundreds of megabytes use `encoding_digests`."""

    def work(batches):
        tok = tokenizer_of(path)
        for key, body in _rows(batches):
            ids = [tok.encode(t) for t in body]
            yield pa.RecordBatch.from_arrays([key, pa.array(ids, pa.list_(pa.int32())), pa.array([tok.decode(i) for i in ids], pa.string())], ["doc_id", "ids", "decoded"])

    return texts(docs, doc_id, text).mapInArrow(work, "doc_id long, ids array<int>, decoded string")


def encoding_digests(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of what `encode_texts` would give, without holding a text's tokens.

    No shuffle: one task per input split, one text at a time. Null and empty texts have no tokens and the digests of the empty string;
    repeated rows are encoded alike; an empty table gives no rows, other columns are ignored. Time grows as n log n with a text's length, long pieces without any split included."""

    def work(batches):
        tok = tokenizer_of(path)
        for key, body in _rows(batches):
            n, ids, words = zip(*map(tok.digest, body), strict=True)
            yield pa.RecordBatch.from_arrays([key, pa.array(n, pa.int64()), pa.array(ids), pa.array(words)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return texts(docs, doc_id, text).mapInArrow(work, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def token_counts(docs: DataFrame, path: str, limit: int = 2048, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit, by the compiled transducer; null and empty texts have 0 tokens.

    No shuffle; long texts and long pieces go by chunks, one text at a time in a task. Repeated rows are counted alike, an empty table gives no rows; other columns are ignored."""

    def work(batches):
        machine = transducer_of(path)
        for key, body in _rows(batches):
            n = [machine.count(t) for t in body]
            size = [len(t) if t.isascii() else len(t.encode()) for t in body]
            yield pa.RecordBatch.from_arrays([key, pa.array(size, pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return texts(docs, doc_id, text).mapInArrow(work, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
