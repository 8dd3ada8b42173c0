"""Chroma audio fingerprints of a media column, and alignment of recordings.

A recording becomes frames of twelve pitch-class energies. Differences of rectangle sums over that
image, read off its integral image, are quantised to two bits each and packed into one 32-bit integer
a frame. Recordings align where equal integers recur at one offset: an offset histogram proposes the
alignment, and the share of differing bits over the overlap decides. Pairs that the histogram does not
settle are compared at every offset: agreeing bits are correlations, read off products of spectra, and
what comes near the bound is counted bit by bit. Equal fingerprints are one class, so a recording
copied many times is searched and found once.
"""

from __future__ import annotations

import io
import wave
import zlib
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.llm.common import arrow_rows, ints, lean
from graphloom.operators.components import components_of_links, star_edges
from graphloom.plans.scratch import Scratch

FRAME, HOP, RATE = 1024, 256, 4000
LOWEST, HIGHEST = 80.0, 1800.0
SPAN = 8  # frames that a filter may cover
MAX_BIT_ERROR, MIN_VOTES = 0.2, 4
BLOCK = 2048  # fingerprints that are compared with as many others at once, at most
WAVES = 640  # places up to which spectra are products with a matrix of waves


def wav_samples(media: bytes | None) -> np.ndarray:
    """Mono samples in [-1, 1] of a 16-bit PCM WAV; broken or missing media are silent and empty."""
    try:
        with wave.open(io.BytesIO(media or b"")) as w:
            if w.getsampwidth() != 2:
                return np.zeros(0)
            x = np.frombuffer(w.readframes(w.getnframes()), "<i2").astype(float) / 32768
            x = x.reshape(-1, w.getnchannels()).mean(axis=1)
            return x if w.getframerate() == RATE else np.interp(np.arange(0, len(x), w.getframerate() / RATE), np.arange(len(x)), x)
    except (wave.Error, EOFError, ValueError):
        return np.zeros(0)


_NOTE = np.arange(HOP) / RATE


def melody(text: str | None) -> np.ndarray:
    """A rendering of a text for tables without audio: one note of 64 ms for each word, pitched by the word."""
    words = (text or "").split()
    if not words:
        return np.zeros(0)
    key = np.array([zlib.crc32(w.encode()) for w in words])
    f = 220 * 2 ** ((key % 25) / 12)
    tone = np.sin(2 * np.pi * f[:, None] * _NOTE) + 0.3 * np.sin(4 * np.pi * f[:, None] * _NOTE)
    return (tone * 0.5).ravel()


def wav_bytes(samples: np.ndarray, rate: int = RATE) -> bytes:
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(2)
        w.setframerate(rate)
        w.writeframes((np.clip(samples, -1, 1) * 32767).astype("<i2").tobytes())
    return out.getvalue()


def _pitch_classes() -> np.ndarray:
    """Which pitch class each FFT bin adds to: bins x 12."""
    f = np.fft.rfftfreq(FRAME, 1 / RATE)
    out = np.zeros((len(f), 12), np.float32)
    ok = np.flatnonzero((f >= LOWEST) & (f <= HIGHEST))
    out[ok, np.rint(12 * np.log2(f[ok] / 440)).astype(int) % 12] = 1
    return out


_CLASSES = _pitch_classes()
_WINDOW = np.hanning(FRAME).astype(np.float32)


def chroma(samples: np.ndarray) -> np.ndarray:
    """Frames x 12 energies of unit norm; a last partial frame is padded with silence. No samples, no frames."""
    if not len(samples):
        return np.zeros((0, 12), np.float32)
    n = max(1, -(-max(0, len(samples) - FRAME) // HOP) + 1)
    x = np.zeros((n - 1) * HOP + FRAME, np.float32)
    x[: len(samples)] = samples[: len(x)]
    frames = np.lib.stride_tricks.sliding_window_view(x, FRAME)[::HOP]
    out = np.zeros((n, 12), np.float32)
    for lo in range(0, n, 512):
        energy = np.abs(np.fft.rfft(frames[lo : lo + 512] * _WINDOW, axis=1)).astype(np.float32) ** 2
        out[lo : lo + 512] = energy @ _CLASSES
    return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-6)


#: Sixteen filters by rule: kind of difference, first pitch class, height, and width in frames.
_FILTERS = [(k % 4, (5 * k) % 12, 2 + k % 5, (2, 4, 6, 8)[(k // 4) % 4]) for k in range(16)]


def _boxes() -> tuple[np.ndarray, ...]:
    """Rectangles of the filters' two sides as 4 x 16, and the other two quarters of the diagonal ones."""
    first, second, first_too, second_too = [], [], [], []
    for kind, y, h, w in _FILTERS:
        if kind == 0:  # earlier against later
            a, b = (0, w // 2, y, y + h), (w // 2, w, y, y + h)
        elif kind == 1:  # lower against higher
            a, b = (0, w, y, y + h // 2), (0, w, y + h // 2, y + h)
        elif kind == 2:  # diagonal quarters
            a, b = (0, w // 2, y, y + h // 2), (0, w // 2, y + h // 2, y + h)
            first_too.append((w // 2, w, y + h // 2, y + h))
            second_too.append((w // 2, w, y, y + h // 2))
        else:  # the band against the whole
            a, b = (0, w, y, y + h), (0, w, 0, 12)
        first.append(a)
        second.append(b)
    return tuple(np.array(x).T for x in (first, second, first_too, second_too))


_FIRST, _SECOND, _FIRST_TOO, _SECOND_TOO = _boxes()
_QUARTERS = [i for i, f in enumerate(_FILTERS) if f[0] == 2]
_SHARE = np.array([h / 12 if kind == 3 else 1.0 for kind, _, h, _ in _FILTERS])


def _responses(image: np.ndarray) -> np.ndarray:
    """Frames x 16 filter responses; the image is repeated upwards by an octave and onwards by its last frame."""
    n = len(image)
    wide = np.concatenate([np.concatenate([image, image], axis=1), np.repeat(np.concatenate([image[-1:], image[-1:]], axis=1), SPAN, axis=0)])
    total = np.zeros((wide.shape[0] + 1, 25))
    total[1:, 1:] = wide.cumsum(axis=0).cumsum(axis=1)
    t = np.arange(n)[:, None]

    def box(sides):  # of all filters at once: frames from, to, pitch classes from, to
        t0, t1, y0, y1 = sides
        return total[t + t1, y1] - total[t + t0, y1] - total[t + t1, y0] + total[t + t0, y0]

    a, b = box(_FIRST), box(_SECOND)
    a[:, _QUARTERS] += box(_FIRST_TOO)
    b[:, _QUARTERS] += box(_SECOND_TOO)
    return np.log1p(np.maximum(a, 0)) - np.log1p(np.maximum(b * _SHARE, 0))


def fingerprint(samples: np.ndarray) -> np.ndarray:
    """One unsigned 32-bit integer a frame: sixteen two-bit levels in Gray code."""
    image = chroma(samples)
    if not len(image):
        return np.zeros(0, np.uint32)
    level = np.digitize(_responses(image), (-0.25, 0.0, 0.25)).astype(np.uint32)
    gray = level ^ (level >> 1)
    return (gray << np.arange(0, 32, 2, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


PRINTED = "rec_id bigint, frames int, digest bigint, print binary"


def fingerprint_column(recordings: DataFrame, id_col: str, media_col: str, decode: Callable = wav_samples) -> DataFrame:
    """rec_id, frames, digest, print: the whole fingerprint of each row's media. Null or unreadable media have no frames."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            prints = [fingerprint(decode(m)) for m in b.column(1).to_pylist()]
            raw = [p.tobytes() for p in prints]
            digest = [zlib.crc32(r) << 31 ^ zlib.adler32(r) for r in raw]
            yield arrow_rows(PRINTED, {"rec_id": b.column(0), "frames": np.array([len(p) for p in prints], np.int32), "digest": digest, "print": raw})

    return recordings.select(recordings[id_col].cast("bigint"), recordings[media_col]).mapInArrow(lean(run), PRINTED)


def _heard(prints: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Integer, recording and frame of the sounds of some recordings, by recording. A held sound begins once, and votes once."""
    sizes = np.array([len(p) for p in prints])
    flat, row, at = np.concatenate(prints), np.repeat(np.arange(len(prints)), sizes), _ranges(np.zeros(len(sizes), np.int64), sizes)
    fresh = np.r_[True, flat[1:] != flat[:-1]] | (at == 0)
    return flat[fresh], row[fresh], at[fresh]


def voted_offsets(queries: list[np.ndarray], matches: list[np.ndarray], min_votes: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(query, match, offset) as arrays: each pair's offset of the most equal integers (ties: nearest 0), if min_votes of them agree, or all in shorter recordings."""
    qs, ms = np.array([len(p) for p in queries]), np.array([len(p) for p in matches])
    most, width = int(qs.max()), int(qs.max() + ms.max())
    asked, query, start = _heard(queries)
    word, row, at = _heard(matches)
    order = np.argsort(word, kind="stable")
    word, row, at = word[order], row[order], at[order]
    lo = np.searchsorted(word, asked, "left")
    size = np.searchsorted(word, asked, "right") - lo
    query, start, lo, size = (x[size > 0] for x in (query, start, lo, size))
    ends = np.cumsum(size)
    keys, votes = np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = 0
    while first < len(query):  # about a million votes at a time
        last = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + (1 << 20), "right")))
        k, hit = slice(first, last), _ranges(lo[first:last], size[first:last])
        offset = at[hit] - np.repeat(start[k], size[k])
        cell, n = np.unique((np.repeat(query[k], size[k]) * len(matches) + row[hit]) * width + offset + most, return_counts=True)
        keys, place = np.unique(np.concatenate([keys, cell]), return_inverse=True)
        votes = np.bincount(place, np.concatenate([votes, n]), len(keys)).astype(np.int64)
        done = int(np.searchsorted(keys, query[last] * len(matches) * width)) if last < len(query) else len(keys)
        pair, offset, n = keys[:done] // width, keys[:done] % width - most, votes[:done]
        keys, votes, first = keys[done:], votes[done:], last
        best = np.lexsort((-offset, np.abs(offset), -n, pair))
        best = best[np.r_[True, pair[best][1:] != pair[best][:-1]]] if done else best
        q, m = pair[best] // len(matches), pair[best] % len(matches)
        enough = n[best] >= np.minimum(min_votes, np.minimum(qs[q], ms[m]))
        if enough.any():
            yield q[enough], m[enough], offset[best][enough]


def _block_of(side: str) -> str:
    return ", ".join(f"{side}_{c} binary" for c in ("ids", "rows", "sizes", "prints"))


def _blocks(side: str, most: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(cls, print, rows) -> one row for up to `most` fingerprints or about 1 MB of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cls, prints, rows = ints(b.column(0)).astype(np.int64), b.column(1).to_pylist(), ints(b.column(2)).astype(np.int64)
            ends = np.cumsum([len(p) for p in prints])
            lo = 0
            while lo < len(prints):
                full = int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + (1 << 20), "right"))
                hi = max(lo + 1, min(lo + most, full))
                sizes = np.array([len(p) // 4 for p in prints[lo:hi]], np.int32)
                yield arrow_rows(_block_of(side), {f"{side}_ids": [cls[lo:hi].tobytes()], f"{side}_rows": [rows[lo:hi].tobytes()], f"{side}_sizes": [sizes.tobytes()], f"{side}_prints": [b"".join(prints[lo:hi])]})
                lo = hi

    return run


def _groups(sizes: np.ndarray, most: int) -> Iterator[np.ndarray]:
    """Rows of like length from the shortest up, `most` of them or fewer where they are long."""
    rows = np.argsort(sizes, kind="stable")
    lo = 0
    while lo < len(rows):
        least = int(sizes[rows[lo]])
        like = int(np.searchsorted(sizes[rows], least + least // 4 + 4, "right"))
        hi = min(lo + max(1, min(most, (1 << 17) // max(least, 1))), like)
        yield rows[lo:hi]
        lo = hi


@lru_cache(maxsize=48)
def _waves(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Cosines and sines of an odd number n of places: frequencies x places."""
    angle = 2 * np.pi / n * (np.arange((n + 1) // 2)[:, None] * np.arange(n) % n)
    return np.cos(angle).astype(np.float32), np.sin(angle).astype(np.float32)


def _signs(prints: list[np.ndarray]) -> np.ndarray:
    """frames x 32 x rows: each bit as 1 or -1, zeros after a row's end."""
    x = np.zeros((max(len(p) for p in prints), 32, len(prints)), np.float32)
    for i, p in enumerate(prints):
        x[: len(p), :, i] = ((p[:, None] >> np.arange(32, dtype=np.uint32)) & 1).astype(np.float32) * 2 - 1
    return x


def _spectra(signs: np.ndarray, n: int) -> np.ndarray:
    """frequencies x 64 x rows: real parts of the 32 bits' spectra at n places, then imaginary ones. Short ones are products with waves."""
    frames, _, rows = signs.shape
    flat = signs.reshape(frames, 32 * rows)
    if n <= WAVES:
        c, s = _waves(n)
        out = np.stack([c[:, :frames] @ flat, -(s[:, :frames] @ flat)], axis=1)
    else:
        z = np.fft.rfft(flat, n, axis=0)
        out = np.stack([z.real, z.imag], axis=1).astype(np.float32)
    return out.reshape(-1, 64, rows)


def _agreement(asked: np.ndarray, spectra: np.ndarray, n: int, offsets: np.ndarray) -> np.ndarray:
    """offsets x queries x matches: agreeing less differing bits. asked: frequencies x 2 queries x 64, the rows of real parts first."""
    found = asked @ spectra
    f, q, m = len(found), found.shape[1] // 2, found.shape[2]
    if n > WAVES:
        found = found.reshape(f, 2, q, m)
        return np.fft.irfft(found[:, 0] + 1j * found[:, 1], n, axis=0)[offsets % n]
    c, s = _waves(n)
    turn = np.stack([c[:, offsets % n], -s[:, offsets % n]], axis=1) * np.float32(2 / n)
    turn[0] /= 2
    return (turn.reshape(2 * f, -1).T @ found.reshape(2 * f, q * m)).reshape(-1, q, m)


def _ranges(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Places first, first + 1, ... of each range, end to end."""
    return np.arange(size.sum()) + np.repeat(first - np.r_[0, np.cumsum(size)[:-1]], size)


def _bit_errors(left: np.ndarray, left_at: np.ndarray, right: np.ndarray, right_at: np.ndarray, overlap: np.ndarray) -> np.ndarray:
    """Share of differing bits of runs of so many frames."""
    error = np.empty(len(overlap))
    ends = np.cumsum(overlap)
    first = 0
    while first < len(overlap):  # about a million frames at a time
        last = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + (1 << 20), "right")))
        size = overlap[first:last]
        wrong = np.bitwise_count(left[_ranges(left_at[first:last], size)] ^ right[_ranges(right_at[first:last], size)])
        error[first:last] = np.add.reduceat(wrong, np.cumsum(size) - size, dtype=np.int64) / (32 * size)
        first = last
    return error


def near_offsets(queries: list[np.ndarray], matches: list[np.ndarray], max_bit_error: float) -> Iterator[tuple[np.ndarray, ...]]:
    """(query, match, offset, overlap, bit_error) as arrays: each pair that some offset aligns within the bound over half of the shorter one; the
    offset of least error (ties: most overlap, nearest 0, least). Nothing is passed over: spectra only tell where counting is needed.

    Groups of like length are compared at as many places as offsets of enough overlap need: sums that run round the end meet no such offset.
    """
    qs, ms = np.array([len(p) for p in queries]), np.array([len(p) for p in matches])
    q_at, m_at = np.cumsum(qs) - qs, np.cumsum(ms) - ms
    q_flat, m_flat = np.concatenate(queries), np.concatenate(matches)
    share = 32 * (1 - 2 * max_bit_error)
    others = [(mi, _signs([matches[i] for i in mi])) for mi in _groups(ms, 128)]
    for qi in _groups(qs, 64):
        signs, kept, asked = _signs([queries[i] for i in qi]), 0, None
        least_q, most_q = int(qs[qi].min()), int(qs[qi].max())
        for mi, other in others:
            least_m, most_m = int(ms[mi].min()), int(ms[mi].max())
            half = (min(least_q, least_m) + 1) // 2
            n = (most_q + most_m - half) // 16 * 16 + 17
            n = n if n <= WAVES else 1 << (n - 1).bit_length()
            if n != kept:
                x = _spectra(signs, n).transpose(0, 2, 1)
                kept, asked = n, np.concatenate([x, np.concatenate([-x[:, :, 32:], x[:, :, :32]], axis=2)], axis=1)
            offsets = np.arange(half - most_q, most_m - half + 1)
            same = _agreement(asked, _spectra(other, n), n, offsets)
            slack = 1 + 1e-4 * 32 * np.sqrt(float(most_q) * most_m)
            overlap = np.maximum(half, np.minimum(least_q, least_m - offsets) - np.maximum(0, -offsets))  # at least, of any pair here
            at = np.flatnonzero(same.reshape(len(offsets), -1) >= (share * overlap - slack).astype(np.float32)[:, None])
            if not len(at):
                continue
            o, a, c = np.unravel_index(at, same.shape)
            q, r, o, same = qi[a], mi[c], offsets[o], same.ravel()[at]
            lo = np.maximum(0, -o)
            overlap = np.minimum(qs[q], ms[r] - o) - lo
            near = np.flatnonzero((2 * overlap >= np.minimum(qs[q], ms[r])) & (same >= share * overlap - slack))
            if not len(near):
                continue
            q, r, o, lo, overlap = (x[near] for x in (q, r, o, lo, overlap))
            error = _bit_errors(q_flat, q_at[q] + lo, m_flat, m_at[r] + lo + o, overlap)
            k = np.flatnonzero(error <= max_bit_error)
            k = k[np.lexsort((o[k], np.abs(o[k]), -overlap[k], error[k], r[k], q[k]))]
            k = k[np.r_[True, (q[k][1:] != q[k][:-1]) | (r[k][1:] != r[k][:-1])]] if len(k) else k
            if len(k):
                yield q[k], r[k], o[k], overlap[k], error[k]


def aligned_offsets(queries: list[np.ndarray], matches: list[np.ndarray], max_bit_error: float, min_votes: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(query, match, offset, overlap, bit_error) as arrays: pairs that votes settle within the bounds, then the others that some offset aligns."""
    qs, ms = np.array([len(p) for p in queries]), np.array([len(p) for p in matches])
    q_at, m_at, q_flat, m_flat = np.cumsum(qs) - qs, np.cumsum(ms) - ms, np.concatenate(queries), np.concatenate(matches)
    settled = np.zeros((len(queries), len(matches)), bool)
    for q, m, o in voted_offsets(queries, matches, min_votes):
        lo = np.maximum(0, -o)
        overlap = np.minimum(qs[q], ms[m] - o) - lo
        half = 2 * overlap >= np.minimum(qs[q], ms[m])
        q, m, o, lo, overlap = (x[half] for x in (q, m, o, lo, overlap))
        error = _bit_errors(q_flat, q_at[q] + lo, m_flat, m_at[m] + lo + o, overlap)
        near = error <= max_bit_error
        settled[q[near], m[near]] = True
        if near.any():
            yield q[near], m[near], o[near], overlap[near], error[near]
    for part in near_offsets(queries, matches, max_bit_error):
        missed = ~settled[part[0], part[1]]
        if missed.any():
            yield tuple(x[missed] for x in part)


def _pairs_of(batches: Iterator[pa.RecordBatch], max_bit_error: float, min_votes: int) -> Iterator[dict[str, np.ndarray]]:
    """Aligned pairs of the classes of each row's two blocks, some at a time."""

    def cut(ids: bytes, rows: bytes, sizes: bytes, prints: bytes) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        return np.frombuffer(ids, np.int64), np.frombuffer(rows, np.int64), np.split(np.frombuffer(prints, np.uint32), np.cumsum(np.frombuffer(sizes, np.int32))[:-1])

    for b in batches:
        for i in range(b.num_rows):
            row = [b.column(j)[i].as_py() for j in range(8)]
            (qids, n_queries, queries), (mids, n_copies, matches) = cut(*row[:4]), cut(*row[4:])
            for q, m, o, n, e in aligned_offsets(queries, matches, max_bit_error, min_votes):
                yield {"query_class": qids[q], "match_class": mids[m], "offset": o.astype(np.int32), "overlap": n.astype(np.int32), "bit_error": e, "n_queries": n_queries[q], "n_copies": n_copies[m]}


PAIRS = "query_class bigint, match_class bigint, offset int, overlap int, bit_error double, n_queries bigint, n_copies bigint"
AS_MATCH, AS_QUERY, STAR = 0, 1, 2
LINKS = "kind int, cls bigint, other bigint, offset int, overlap int, bit_error double, n_links bigint"
HELD = 500_000  # rows that a task sums at once


def _summed(parts: list[dict[str, np.ndarray]]) -> dict[str, np.ndarray]:
    """One row for each kind and class: its links, and its alignment of least error (ties: most overlap, least other class, least offset)."""
    x = {c: np.concatenate([p[c] for p in parts]) for c in parts[0]}
    order = np.lexsort((x["offset"], x["other"], -x["overlap"], x["bit_error"], x["cls"], x["kind"]))
    x = {c: v[order] for c, v in x.items()}
    first = np.flatnonzero(np.r_[True, (x["cls"][1:] != x["cls"][:-1]) | (x["kind"][1:] != x["kind"][:-1])])
    return {c: v[first] for c, v in x.items()} | {"n_links": np.add.reduceat(x["n_links"], first)}


def _link(max_bit_error: float, min_votes: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """LINKS rows of a task's pairs, of which none leaves it: sums of each class, as a match and as a query, and stars of the classes they join."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[dict[str, np.ndarray]] = []
        stars, n = np.zeros((2, 0), np.int64), 0

        def out(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
            for lo in range(0, len(x["cls"]), 50_000):
                yield arrow_rows(LINKS, {c: v[lo : lo + 50_000] for c, v in x.items()})

        def joined() -> dict[str, np.ndarray]:
            zero = np.zeros(stars.shape[1], np.int32)
            return {"kind": zero + np.int32(STAR), "cls": stars[0], "other": stars[1], "offset": zero, "overlap": zero, "bit_error": zero.astype(float), "n_links": zero.astype(np.int64)}

        for p in _pairs_of(batches, max_bit_error, min_votes):
            p = {c: v[p["query_class"] != p["match_class"]] for c, v in p.items()}
            size = len(p["offset"])
            if not size:
                continue
            both = {"overlap": p["overlap"], "bit_error": p["bit_error"]}
            held.append({"kind": np.full(size, AS_MATCH, np.int32), "cls": p["match_class"], "other": p["query_class"], "offset": -p["offset"], "n_links": p["n_queries"], **both})
            held.append({"kind": np.full(size, AS_QUERY, np.int32), "cls": p["query_class"], "other": p["match_class"], "offset": p["offset"], "n_links": p["n_copies"], **both})
            stars = np.concatenate([stars, np.stack([p["match_class"], p["query_class"]])], axis=1)
            n += 2 * size
            if n > HELD:
                held = [_summed(held)]
                stars = np.array(star_edges(*stars), np.int64).reshape(2, -1)
                n = len(held[0]["cls"])
                if n > HELD // 2:
                    yield from out(held[0])
                    yield from out(joined())
                    held, stars, n = [], stars[:, :0], 0
        if held:
            stars = np.array(star_edges(*stars), np.int64).reshape(2, -1)
            yield from out(_summed(held))
            yield from out(joined())

    return run


def _classes(scratch: Scratch, printed: DataFrame, is_query) -> tuple[DataFrame, DataFrame]:
    """The rows of printed with `query`, and the classes of those with frames: digest, frames, print, cls, n_copies, n_queries."""
    saved = scratch.save(printed.withColumn("query", F.coalesce(is_query, F.lit(False))), "printed")
    classes = saved.where("frames > 0 and rec_id is not null").groupBy("digest", "frames", "print").agg(F.min("rec_id").alias("cls"), F.count("*").alias("n_copies"), F.sum(F.col("query").cast("bigint")).alias("n_queries"))
    return saved, scratch.save(classes, "classes")


def _block_pairs(scratch: Scratch, classes: DataFrame) -> DataFrame:
    """Blocks of the queries' classes beside blocks of all classes; a block pair is one task's own small problem."""
    parts = int(classes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    block = lambda rows, side, most, n: rows.sortWithinPartitions("frames", "cls").select("cls", "print", n).mapInArrow(lean(_blocks(side, most)), _block_of(side))
    asked = scratch.save(block(classes.where("n_queries > 0").coalesce(1), "query", BLOCK // 4, "n_queries"), "query_blocks")
    others = scratch.save(block(classes.repartition(parts, "cls"), "match", BLOCK, "n_copies"), "match_blocks").repartition(4 * parts)
    return others.crossJoin(asked).select(*asked.columns, *others.columns)


def align_recordings(printed: DataFrame, is_query, max_bit_error: float = MAX_BIT_ERROR, min_votes: int = MIN_VOTES) -> DataFrame:
    """query_class, match_class, offset, overlap, bit_error, n_queries, n_copies.

    A class is all rows with one fingerprint, named by its least id. Each class that holds a query row
    is aligned with every class, its own included (offset 0, no errors): the offset with the most equal
    integers (ties: the least), settled where at least min_votes of them (or all, in shorter recordings)
    agree, the overlap covers half of the shorter recording, and the bit error is at most
    max_bit_error. Any other pair that meets these two bounds at some offset is there with the offset of
    least bit error. Rows without frames are in no class. The pairs grow with queries times recordings;
    link_recordings() sums them.
    """
    scratch = Scratch(printed.sparkSession, "chroma")
    _, classes = _classes(scratch, printed, is_query)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for p in _pairs_of(batches, max_bit_error, min_votes):
            yield arrow_rows(PAIRS, p)

    return scratch.save(_block_pairs(scratch, classes).mapInArrow(lean(run), PAIRS), "pairs")


def link_recordings(printed: DataFrame, is_query, max_bit_error: float = MAX_BIT_ERROR, min_votes: int = MIN_VOTES) -> DataFrame:
    """One row for each row of printed: rec_id, class_id, query, n_links, component_id, match_class, offset, overlap, bit_error.

    The pairs are those of align_recordings(), every one of them, but they are summed where they are found.
    class_id is the least id of the rows with the same fingerprint. n_links counts the other rows that a query
    row aligns with, its copies too, or the query rows that any other row aligns with. component_id is the
    least id of the classes joined by alignments. The last four are of the class of another fingerprint that aligns with
    the least bit error (ties: most overlap, least class): frame i lies at its frame i + offset. Rows without frames have
    no class, no links and their own id as component.
    """
    scratch = Scratch(printed.sparkSession, "chroma")
    saved, classes = _classes(scratch, printed, is_query)
    linked = scratch.save(_block_pairs(scratch, classes).mapInArrow(lean(_link(max_bit_error, min_votes)), LINKS), "linked")
    best = F.min(F.struct("bit_error", (-F.col("overlap")).alias("wide"), "other", "offset", "overlap"))
    sums = lambda kind, to: linked.where(F.col("kind") == kind).groupBy("cls").agg(F.sum("n_links").alias(f"{to}_links"), best.alias(to))
    joined = components_of_links(linked.where(F.col("kind") == STAR).select("cls", "other")).withColumnsRenamed({"id": "cls"})
    known = classes.join(sums(AS_MATCH, "asked"), "cls", "left").join(sums(AS_QUERY, "all"), "cls", "left").join(joined, "cls", "left")
    rows = saved.join(known, ["digest", "frames", "print"], "left")
    found = lambda c: F.when(F.col("query"), F.col(f"all.{c}")).otherwise(F.col(f"asked.{c}"))
    n_links = F.when(F.col("query"), F.coalesce("all_links", F.lit(0)) + F.col("n_copies") - 1).otherwise(F.coalesce("asked_links", F.lit(0)) + F.col("n_queries"))
    return rows.select(
        "rec_id",
        F.col("cls").alias("class_id"),
        "query",
        F.coalesce(n_links, F.lit(0)).cast("bigint").alias("n_links"),
        F.coalesce("component", "cls", "rec_id").alias("component_id"),
        found("other").alias("match_class"),
        *[found(c).alias(c) for c in ("offset", "overlap", "bit_error")],
    )
