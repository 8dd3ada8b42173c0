"""BPE encoding and decoding by a tokenization automaton.

The merge list is compiled into a deterministic automaton over tokens. Its states are the tokens
(the last arc taken), and each merge adds one gadget: arcs labelled with the merged token, and the
removal of the arc of the right part from every state that the left part has reached by then. The
surviving paths spell each word in exactly one way, its BPE tokenization.

A fully expanded arc table has |V|^2 entries, nearly all present, so gadgets are kept as they are
made: for each token its spine of parts with the merge steps between which each part stood alone,
and for each left part its removed right parts with their step. An arc is expanded on first use and
then looked up. Words are spelt left to right: for each prefix, the one token that can end it.
"""

from __future__ import annotations

import hashlib
import json
import threading
import unicodedata
import zlib
from array import array
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from graphloom.llm.common import arrow_rows, by_bytes, joined_bytes, lean, slices, trim
from graphloom.llm.shingles import _RAW_BYTE, U, word_hashes

#: Spaces of Unicode, by which the vocabulary's normalizer and word pattern split. Fixed values.
_SPACES = "\t\n\x0b\x0c\r \x85\xa0  -     　"
_ODD = regex.compile("[\x1c-\x1f]")  # str.split() takes these for spaces
_RUN = regex.compile(f"[^{_SPACES}]+")
#: Entries that a worker's memory of chunks holds before its older half is let go (a word's and prefix's memory: half of that).
CACHE_CHUNKS = 100_000
_SLOTS = 20  # bits of a slot of the chunk memory, which is emptied when 5/8 full


def fold(text: str) -> str:
    """Composed form, lower-cased symbol by symbol as the vocabulary's normalizer does (no final-sigma rule)."""
    if not unicodedata.is_normalized("NFC", text):
        text = unicodedata.normalize("NFC", text)
    return text.lower() if "Σ" not in text else "".join([c.lower() for c in text])


class Memory(dict):
    """A memo of a function in two generations: what is used again outlives the change of generation."""

    def __init__(self, compute, most: int):
        super().__init__()
        self.compute, self.most, self.old = compute, most, {}

    def __missing__(self, key: str):
        value = self.old.get(key)
        if value is None:
            value = self.compute(key)
        if len(key) <= 40:
            self.keep(key, value)
        return value

    def keep(self, key: str, value: bytes) -> None:
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        self[key] = value


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class TokenAutomaton:
    """A word-end BPE vocabulary file (tokenizers JSON) compiled as said above."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.end: str = model["end_of_word_suffix"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.word = regex.compile(next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split"))
        self.symbols = byte_symbols()
        self.labels: list[bytes] = [b""] * (max([*self.vocab.values(), *self.special.values()]) + 1)
        for text, i in [*self.vocab.items(), *self.special.items()]:
            self.labels[i] = text.encode()
        self._special = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self._marks = tuple({s[:2] for s in self.special})
        self._compile([tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]])
        self.release()

    def release(self) -> None:
        """Let go of the memories: of chunks' ids, words' ids, states by prefix, and expanded arcs. Workers idle on after their task."""
        self.cache = Memory(self._chunk, CACHE_CHUNKS)
        self.words = Memory(self._word, CACHE_CHUNKS // 2)
        self.states: dict[str, int] = {}
        if len(getattr(self, "arcs", ())) > 2 * CACHE_CHUNKS or not hasattr(self, "arcs"):
            self.arcs: dict[int, bool] = {}
        self.pool = None

    def _compile(self, merges: list[tuple[str, str]]) -> None:
        size, never = len(self.labels), len(merges) + 1
        #: For each token: its last parts (right spine) and first parts (left spine), each with the steps between which it stands alone.
        self.right: list[list[tuple[int, int, int]]] = [[(t, -1, never)] for t in range(size)]
        self.left: list[list[tuple[int, int, int]]] = [[(t, -1, never)] for t in range(size)]
        #: removed[u][v]: the step whose gadget takes arc v from the states that u has reached.
        self.removed: dict[int, dict[int, int]] = {}
        made: set[int] = set()
        for step, (u_text, v_text) in enumerate(merges):
            u, v, w = self.vocab[u_text], self.vocab[v_text], self.vocab[u_text + v_text]
            self.removed.setdefault(u, {})[v] = step
            if w not in made:  # a second way to the same token is never taken: its arcs are gone by then
                made.add(w)
                self.right[w] = [*((t, a, min(b, step)) for t, a, b in self.right[v]), (w, step, never)]
                self.left[w] = [*((t, a, min(b, step)) for t, a, b in self.left[u]), (w, step, never)]
        self.width = [len(x.decode().removesuffix(self.end)) for x in self.labels]
        #: For up to five last symbols of a text (and the end mark): length of the longest token that ends so.
        self.reach: dict[str, int] = {}
        for text, label in self.vocab.items():
            tail = self.end if text.endswith(self.end) and text != self.end else ""
            body = text.removesuffix(tail)
            for k in range(1, 6):
                if len(body) >= k:
                    self.reach[body[-k:] + tail] = max(self.reach.get(body[-k:] + tail, 0), self.width[label])

    def arc(self, state: int, label: int) -> bool:
        """Whether the automaton has an arc with this label from the state that the token state reaches."""
        for u, u_from, u_to in self.right[state]:
            if gone := self.removed.get(u):
                for v, v_from, v_to in self.left[label]:
                    step = gone.get(v)
                    # equal steps: the leftmost occurrence merges first, inside the state's own token
                    if step is not None and u_from < step < u_to and v_from < step <= v_to:
                        return False
        return True

    def _last(self, word: str, i: int, last: list[int], tail: str) -> int:
        """The only token that can end the path over word[:i]; last has those of the shorter prefixes."""
        vocab, arcs, reach = self.vocab, self.arcs, self.reach
        head = word[:i] + tail
        span = min(i, 5)
        longest = reach.get(head[i - span :])
        while longest is None:
            span -= 1
            longest = span if head[i - span :] in reach else None
        for j in range(i - longest if longest < i else 0, i):
            label = vocab.get(head[j:])
            if label is None:
                continue
            if not j:
                if self._whole(label):
                    return label
                continue
            key = last[j] << 17 | label
            ok = arcs.get(key)
            if ok is None:
                ok = arcs[key] = self.arc(last[j], label)
            if ok:
                return label
        raise ValueError(f"no path spells {word!r}")

    def spell(self, word: str) -> list[int]:
        """Labels on the only path that spells a word, given in byte symbols without the end mark."""
        n, states, last = len(word), self.states, [-1]
        for i in range(1, n):
            head = word[:i]
            state = states.get(head)
            if state is None:
                state = self._last(word, i, last, "")
                if i <= 24:
                    states[head] = state
            last.append(state)
        label = self._last(word, n, last, self.end)
        out, i, width = [label], n - self.width[label], self.width
        while i:
            label = last[i]
            out.append(label)
            i -= width[label]
        out.reverse()
        return out

    # ---- the same transitions for many words at once ----

    def _tables(self) -> None:
        """Tokens of common bytes as a trie over their reversed bytes (a word's end first), and a direct-mapped memory of arcs."""
        code = np.zeros(256, np.uint8)
        common = [*b"abcdefghijklmnopqrstuvwxyz", 0xC3, *range(0x80, 0xC0)]
        code[common] = np.arange(1, len(common) + 1)
        byte_of = {c: b for b, c in enumerate(self.symbols)}
        self.code, self.common, end = code, bytes(common), len(common) + 1
        steps: dict[int, int] = {}  # (node, code) -> node
        token = [-1]
        for text, label in self.vocab.items():
            body = text.removesuffix(self.end) or text
            raw = bytes(byte_of[c] for c in body)
            if raw.translate(None, self.common) or (self.width[label] > 1 and len(self.right[label]) == 1):
                continue
            at = 0
            for c in ([end] if body != text else []) + [int(code[b]) for b in reversed(raw)]:
                step = at << 8 | c
                at = steps.get(step, 0)
                if not at:
                    at = steps[step] = len(token)
                    token.append(-1)
            token[at] = label
        self.next = np.zeros((len(token), end + 1), np.int32)
        known = np.array(list(steps.items()), np.int64).reshape(-1, 2)
        self.next[known[:, 0] >> 8, known[:, 0] & 255] = known[:, 1]
        self.token, self.end_node = np.array(token, np.int32), int(self.next[0, end])
        self.widths = np.array(self.width, np.int32)
        self.arc_keys, self.arc_open = np.full(1 << 20, -1, np.int64), np.zeros(1 << 20, bool)

    def _open(self, state: np.ndarray, label: np.ndarray) -> np.ndarray:
        """arc() of many pairs."""
        key = state.astype(np.int64) << 17 | label
        slot = (key * -7046029254386353131 >> 44) & ((1 << 20) - 1)
        ok = self.arc_open[slot]
        miss = np.flatnonzero(self.arc_keys[slot] != key)
        if len(miss):
            fresh, back = np.unique(key[miss], return_inverse=True)
            arcs, values = self.arcs, np.empty(len(fresh), bool)
            for i, k in enumerate(fresh.tolist()):
                value = arcs.get(k)
                if value is None:
                    value = arcs[k] = self.arc(k >> 17, k & 131071)
                values[i] = value
            ok[miss] = values[back]
            self.arc_keys[slot[miss]], self.arc_open[slot[miss]] = key[miss], ok[miss]
        return ok

    def _advance(self, codes: np.ndarray, last: np.ndarray, i: int, rows: np.ndarray, node: int) -> None:
        """Fill last[i] of the rows: walk the trie back from position i until the one open token is found."""
        at = np.full(len(rows), node, np.int32)
        for j in range(i - 1, -1, -1):
            at = self.next[at, codes[j, rows]]
            alive = at > 0
            if not alive.all():
                rows, at = rows[alive], at[alive]
            if not len(rows):
                return
            label = self.token[at]
            held = np.flatnonzero(label >= 0)
            if len(held):
                found = held if not j else held[self._open(last[j, rows[held]], label[held])]
                last[i, rows[found]] = label[found]
                rest = np.ones(len(rows), bool)
                rest[found] = False
                rows, at = rows[rest], at[rest]

    def spell_many(self, words: list[bytes]) -> tuple[list[bytes], list[bytes]]:
        """The words, longest first, and their ids: words of common bytes, each position of all words in one pass of array look-ups."""
        if not hasattr(self, "next"):
            self._tables()
        words = sorted(words, key=len, reverse=True)
        sizes = np.array([len(w) for w in words])
        longest = int(sizes[0])
        flat = np.frombuffer(b"".join([w.ljust(longest, b"\0") for w in words]), np.uint8)
        codes = np.ascontiguousarray(self.code[flat].reshape(-1, longest).T)
        last = np.full((longest + 1, len(words)), -1, np.int32)
        for i in range(1, longest + 1):
            inside, ending = int((sizes > i).sum()), int((sizes >= i).sum())
            self._advance(codes, last, i, np.arange(inside), 0)
            self._advance(codes, last, i, np.arange(inside, ending), self.end_node)
        rows, place, steps = np.arange(len(words)), sizes.copy(), []
        count = np.zeros(len(words), np.int64)
        while len(rows):
            label = last[place[rows], rows]
            steps.append((rows, label))
            count[rows] += 1
            place[rows] -= self.widths[label]
            rows = rows[place[rows] > 0]
        stop = np.cumsum(count)
        ids = np.empty(int(stop[-1]), np.uint32)
        for k, (rows, label) in enumerate(steps):
            ids[stop[rows] - 1 - k] = label
        raw, bounds = ids.tobytes(), [0, *(4 * stop).tolist()]
        return words, [raw[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]

    def _spell_chunks(self, chunks: list[str]) -> list[bytes]:
        """Ids of runs without spaces; their new words of common bytes are spelt together."""
        words = self.words
        plain: list[tuple[str, str]] = []
        fresh: dict[bytes, str] = {}
        for chunk in chunks:
            word = chunk.lower() if chunk.isascii() else fold(chunk)
            tail = word[-1] if word[-1:] in (".", ",") else ""
            word = word[:-1] if tail else word
            if not word.isalpha() or len(word) > 24:
                plain.append(("", chunk))
                continue
            plain.append((word, tail))
            if word not in words and word not in words.old:
                raw = word.encode("utf-8", "replace")
                if not raw.translate(None, self.common):
                    fresh[raw] = word
        if fresh:
            for raw, ids in zip(*self.spell_many(list(fresh)), strict=True):
                words.keep(fresh[raw], ids)
        return [(words[w] + words[x] if x else words[w]) if w else self._chunk(x) for w, x in plain]

    def _forget(self) -> None:
        """An empty memory of chunks: open addressing by hash, and a pool of their ids."""
        self.chunk_keys = np.zeros(1 << _SLOTS, U)
        self.chunk_at, self.chunk_len = np.zeros(1 << _SLOTS, np.int32), np.zeros(1 << _SLOTS, np.int32)
        self.pool, self.pooled, self.held = np.zeros(1 << 18, np.uint32), 0, 0

    def _find(self, hashes: np.ndarray) -> np.ndarray:
        """Slot of each hash, -1 where it is not held."""
        slot = (hashes >> U(64 - _SLOTS)).astype(np.int64)
        out = np.full(len(hashes), -1, np.int64)
        todo = np.arange(len(hashes))
        while len(todo):
            here = self.chunk_keys[slot[todo]]
            hit = here == hashes[todo]
            out[todo[hit]] = slot[todo[hit]]
            todo = todo[~hit & (here != 0)]
            slot[todo] = (slot[todo] + 1) & ((1 << _SLOTS) - 1)
        return out

    def _hold(self, hashes: np.ndarray, ids: list[bytes]) -> None:
        size = np.array([len(x) // 4 for x in ids], np.int64)
        flat = np.frombuffer(b"".join(ids), np.uint32)
        while self.pooled + len(flat) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros(len(self.pool), np.uint32)])
        self.pool[self.pooled : self.pooled + len(flat)] = flat
        at = self.pooled + np.cumsum(size) - size
        self.pooled += len(flat)
        self.held += len(ids)
        slot = (hashes >> U(64 - _SLOTS)).astype(np.int64)
        todo = np.arange(len(hashes))
        while len(todo):
            free = todo[self.chunk_keys[slot[todo]] == 0]
            _, first = np.unique(slot[free], return_index=True)
            put = free[first]
            self.chunk_keys[slot[put]], self.chunk_at[slot[put]], self.chunk_len[slot[put]] = hashes[put], at[put], size[put]
            left = np.ones(len(hashes), bool)
            left[put] = False
            todo = todo[left[todo]]
            slot[todo] = (slot[todo] + (self.chunk_keys[slot[todo]] != 0)) & ((1 << _SLOTS) - 1)

    def _encode_slice(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of some texts end to end and their n+1 offsets. Chunks are known by 64-bit hashes; new ones are spelt once."""
        hashes, at, start, end = word_hashes(data, offsets, _RAW_BYTE)
        hashes |= U(1)
        slot = self._find(hashes)
        miss = np.flatnonzero(slot < 0)
        if len(miss):
            new, first = np.unique(hashes[miss], return_index=True)
            if self.held + len(new) > (1 << _SLOTS) * 5 // 8:
                self._forget()
                return self._encode_slice(data, offsets)
            raw = data.tobytes()
            where = miss[first]
            self._hold(new, self._spell_chunks([raw[i:j].decode("utf-8", "replace") for i, j in zip(start[where].tolist(), end[where].tolist(), strict=True)]))
            slot[miss] = self._find(hashes[miss])
        size = self.chunk_len[slot].astype(np.int64)
        before = np.r_[0, np.cumsum(size)]
        take = np.repeat(self.chunk_at[slot].astype(np.int64) - before[:-1], size) + np.arange(before[-1])
        return self.pool[take], before[at]

    def encode_column(self, column: pa.Array) -> list[bytes]:
        """encode() of a column of texts; nulls are empty. Texts with a special string go one by one."""
        for memory in (self.states, self.arcs):
            if len(memory) > 2 * CACHE_CHUNKS:
                memory.clear()
        if not hasattr(self, "next"):
            self._tables()
        if self.pool is None:
            self._forget()
        data, offsets = joined_bytes(column)
        out: list[bytes] = []
        lo, n = 0, len(offsets) - 1
        with np.errstate(over="ignore"):
            while lo < n:
                hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + (1 << 19), "right")) - 1)
                cut = offsets[lo : hi + 1]
                ids, bounds = self._encode_slice(data[cut[0] : cut[-1]], cut - cut[0])
                raw, bounds = ids.tobytes(), (4 * bounds).tolist()
                out += [raw[i:j] for i, j in zip(bounds, bounds[1:], strict=False)]
                lo = hi
        for k, text in self._with_specials(data, offsets):
            out[k] = self.encode(text)
        return out

    def _with_specials(self, data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, str]]:
        raw = data.tobytes() if self.special else b""
        rows = set()
        for special in self.special:
            at = raw.find(special.encode())
            while at >= 0:
                rows.add(int(np.searchsorted(offsets, at, "right")) - 1)
                at = raw.find(special.encode(), at + 1)
        for k in sorted(rows):
            yield k, raw[offsets[k] : offsets[k + 1]].decode("utf-8", "replace")

    def _whole(self, label: int) -> bool:
        """A token that merges can make, from the start state."""
        return len(self.right[label]) > 1 or self.width[label] == 1

    def _word(self, word: str) -> bytes:
        plain = word.isascii() and word.isprintable()
        return array("I", self.spell(word if plain else "".join([self.symbols[b] for b in word.encode("utf-8", "replace")]))).tobytes()

    def _chunk(self, chunk: str) -> bytes:
        """Ids of a run without spaces, as unsigned 32-bit integers."""
        words = self.words
        if chunk.isascii():
            chunk = chunk.lower()
            if chunk.isalpha():
                return words[chunk]
            if chunk[-1] in ".," and chunk[:-1].isalpha():
                return words[chunk[:-1]] + words[chunk[-1]]
        else:
            chunk = fold(chunk)
        return b"".join([words[w] for w in self.word.findall(chunk)])

    def _plain(self, text: str) -> bytes:
        for memory in (self.states, self.arcs):
            if len(memory) > 2 * CACHE_CHUNKS:
                memory.clear()
        cache = self.cache
        return b"".join([cache[c] for c in (text.split() if not _ODD.search(text) else _RUN.findall(text))])

    def encode(self, text: str) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers. Special strings are their own ids."""
        if self._special and any(m in text for m in self._marks) and (parts := self._special.split(text))[1:]:
            return b"".join(array("I", [self.special[p]]).tobytes() if p in self.special else self._plain(p) for p in parts)
        return self._plain(text)

    def decode(self, ids: bytes) -> bytes:
        """The arcs' labels, in UTF-8, parted by single spaces (the vocabulary names no decoder)."""
        labels = self.labels
        return b" ".join([labels[i] for i in array("I", ids)])


_LOADED: dict[str, TokenAutomaton] = {}
_LOCK = threading.Lock()
_IDLE: list[threading.Timer] = []
IDLE_SECONDS = 2.0


def automaton(path: str) -> TokenAutomaton:
    """One automaton for each Python worker and vocabulary file."""
    if path not in _LOADED:
        _LOADED.clear()
        _LOADED[path] = TokenAutomaton(path)
    return _LOADED[path]


def _let_go() -> None:
    with _LOCK:
        if _IDLE and _IDLE[0] is threading.current_thread():
            _LOADED.clear()
            _IDLE.clear()
    trim()


@contextmanager
def borrowed(path: str) -> Iterator[TokenAutomaton]:
    """The worker's automaton for one task. Its memories are let go at the end, and itself soon after unless a next task takes it."""
    with _LOCK:
        for timer in _IDLE:
            timer.cancel()
        _IDLE.clear()
        a = automaton(path)
    try:
        yield a
    finally:
        a.release()
        with _LOCK:
            timer = threading.Timer(IDLE_SECONDS, _let_go)
            timer.daemon = True
            _IDLE[:] = [timer]
            timer.start()


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


ENCODED = "doc_id bigint, ids binary"
DIGESTS = "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string, ids_crc32 bigint"


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids): ids of each whole text as packed 32-bit integers. Null texts are empty; narrow, one row each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with borrowed(path) as a:
            for b in (part for batch in batches for part in slices(batch, 1)):
                yield arrow_rows(ENCODED, {"doc_id": b.column(0), "ids": a.encode_column(b.column(1))})

    return by_bytes(docs).select(docs[id_col].cast("bigint"), docs[text_col]).mapInArrow(lean(run), ENCODED)


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids) -> (doc_id, text)."""
    schema = "doc_id bigint, text string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = automaton(path)
        for b in batches:
            yield arrow_rows(schema, {"doc_id": b.column(0), "text": [a.decode(x or b"").decode("utf-8") for x in b.column(1).to_pylist()]})

    return encoded.select("doc_id", "ids").mapInArrow(lean(run), schema)


def round_trip_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: token count and digests of its ids and of their decoding.

    Null and empty texts have 0 tokens and the digests of the empty string; repeated rows give
    repeated rows; other columns of docs are not read. An empty table gives no rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with borrowed(path) as a:
            for b in (part for batch in batches for part in slices(batch, 1)):
                out: dict[str, list] = {k: [] for k in ("n_tokens", "ids_sha256", "decoded_sha256", "ids_crc32")}
                for ids in a.encode_column(b.column(1)):
                    out["n_tokens"].append(len(ids) // 4)
                    out["ids_sha256"].append(hashlib.sha256(ids).hexdigest())
                    out["decoded_sha256"].append(hashlib.sha256(a.decode(ids)).hexdigest())
                    out["ids_crc32"].append(zlib.crc32(ids))
                yield arrow_rows(DIGESTS, {"doc_id": b.column(0), **out})

    return by_bytes(docs).select(docs[id_col].cast("bigint"), docs[text_col]).mapInArrow(lean(run), DIGESTS)
