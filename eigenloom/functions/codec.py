"""Byte code of a tile: words of 16 bits.

Rows with at least two cells come first, each as a word with bit 15 set that carries the row, followed by its columns in order; rows with
one cell follow as (row, column) pairs; values, if any, are float64 in the same order.
"""

from __future__ import annotations

import numpy as np

MAX_EDGE, MARK = 1 << 15, 1 << 15


def encode(rows: np.ndarray, cols: np.ndarray, values: np.ndarray | None = None, edge: int = 16384, hybrid: bool = True) -> tuple[bytes, bytes | None, int, int]:
    """(code, values or None, rows with several cells, rows with one cell); values that are all 1 are left out."""
    words, ends, stored, _value_ends, multi, single = encode_many(np.array([0, len(rows)]), rows, cols, values, edge, hybrid)
    return words.tobytes(), None if stored is None or not len(stored) else stored.tobytes(), int(multi[0]), int(single[0])


def encode_many(bounds: np.ndarray, rows: np.ndarray, cols: np.ndarray, values: np.ndarray | None = None, edge: int = 16384, hybrid: bool = True):
    """(words, word ends, values, value ends, rows with several cells, rows with one cell) of many tiles in one pass: tile t has the cells bounds[t] to bounds[t + 1], its words end at
    word ends[t], its values at value ends[t]; the values of a tile that are all 1 are left out."""
    if edge > MAX_EDGE:
        raise ValueError(f"a tile edge is at most {MAX_EDGE}")
    rows, cols, tiles = np.asarray(rows).astype(np.int64), np.asarray(cols).astype(np.int64), len(bounds) - 1
    if len(rows) and (rows.min() < 0 or cols.min() < 0 or rows.max() >= edge or cols.max() >= edge):
        raise ValueError("a cell lies outside its tile")
    sizes = np.diff(bounds)
    tile = np.repeat(np.arange(tiles), sizes)
    line = tile * edge + rows
    place = line * edge + cols
    if (place[1:] < place[:-1]).any():
        order = np.argsort(place, kind="stable")
        line, rows, cols = line[order], rows[order], cols[order]
        values = None if values is None else np.asarray(values)[order]
    begins = np.flatnonzero(np.diff(line, prepend=-1))
    counts = np.diff(begins, append=len(line))
    of, several = tile[begins], counts > 1 if hybrid else np.ones(len(begins), bool)
    # Where the words of each row begin: in its tile, rows with several cells before rows with one, both in order.
    lines = np.bincount(of, minlength=tiles)
    multi = np.bincount(of[several], minlength=tiles)
    more, one = np.where(several, counts + 1, 0), np.where(several, 0, 2)
    more_ends, one_ends = np.cumsum(more), np.cumsum(one)
    line_ends = np.cumsum(lines)
    more_in, one_in = (np.diff(np.append(0, x)[np.append(0, line_ends)]) for x in (more_ends, one_ends))
    word_ends = np.cumsum(more_in + one_in)
    # Words of the other kind that lie between the order of the rows and that of the words: singles of tiles before, and for a single also all several of its own tile.
    at = np.where(several, more_ends - more + (np.cumsum(one_in) - one_in)[of], one_ends - one + np.cumsum(more_in)[of])
    words = np.zeros(int(word_ends[-1]) if tiles else 0, np.uint16)
    words[at] = rows[begins] | np.where(several, MARK, 0)
    cell = np.repeat(at + 1 - begins, counts) + np.arange(len(line))
    words[cell] = cols
    stored, value_ends = None, np.zeros(tiles, np.int64)
    if values is not None:
        v = np.asarray(values, "<f8")
        weighted = np.bincount(tile[v != 1], minlength=tiles) > 0
        mine = np.repeat(weighted, sizes)
        held, is_cell = np.zeros(len(words)), np.zeros(len(words), bool)
        held[cell[mine]], is_cell[cell[mine]] = v[mine], True
        stored = held[is_cell]
        value_ends = np.cumsum(np.where(weighted, sizes, 0))
    return words.astype(">u2"), word_ends, stored, value_ends, multi, lines - multi


def decode(code: bytes, values: bytes | None, n_single: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    words = np.frombuffer(code, ">u2").astype(np.int64)
    split = len(words) - 2 * n_single
    several, pairs = words[:split], words[split:].reshape(-1, 2)
    marked = several >= MARK
    rows = np.where(marked, several - MARK, 0)[np.maximum.accumulate(np.where(marked, np.arange(split), 0))] if split else several
    r, c = np.concatenate([rows[~marked], pairs[:, 0]]), np.concatenate([several[~marked], pairs[:, 1]])
    return r, c, np.ones(len(r)) if values is None else np.frombuffer(values, "<f8")


def decode_many(codes: list[bytes], values: list[bytes | None], singles: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(tile's place, rows, cols, weights) of many tiles in one pass; each tile's cells in the order of `decode`."""
    words = np.frombuffer(b"".join(codes), ">u2").astype(np.int64)
    sizes, pairs = np.fromiter(map(len, codes), np.int64, len(codes)) // 2, 2 * np.asarray(singles, np.int64)
    ends = np.cumsum(sizes)
    paired = np.zeros(len(words), np.int64)  # words of the section of one-cell rows
    np.add.at(paired, (ends - pairs)[pairs > 0], 1)
    np.add.at(paired, ends[(pairs > 0) & (ends < len(words))], -1)
    paired = np.cumsum(paired) > 0
    place = np.repeat(np.arange(len(codes)), sizes)
    offset = np.arange(len(words)) - np.repeat(ends - pairs, sizes)
    head = np.where(paired, offset % 2 == 0, words >= MARK)
    heads = np.where(paired, words, words - MARK)
    rows = heads[np.maximum.accumulate(np.where(head, np.arange(len(words)), 0))]
    cell = ~head
    place, rows, cols = place[cell], rows[cell], words[cell]
    weights = np.ones(len(rows))
    held = np.fromiter((v is not None for v in values), bool, len(codes))
    if held.any():
        weights[held[place]] = np.frombuffer(b"".join(v for v in values if v is not None), "<f8")
    return place, rows, cols, weights


def multiply_into(out: np.ndarray, rows: np.ndarray, cols: np.ndarray, weights: np.ndarray, dense: np.ndarray, vectorised: bool = True) -> None:
    """out[rows] += weights * dense[cols]; rows need not be unique."""
    if not len(rows):
        return
    if not vectorised:
        for r, c, w in zip(rows, cols, weights):
            out[r] += w * dense[c]
        return
    least = rows.min()
    span = int(rows.max() - least) + 1
    if span <= 4 * len(rows):
        r, terms = rows - least, dense[cols] * weights[:, None]
        for k in range(terms.shape[1]):
            out[least : least + span, k] += np.bincount(r, terms[:, k], span)
        return
    order = np.argsort(rows, kind="stable")
    r = rows[order]
    starts = np.flatnonzero(np.diff(r, prepend=-1))
    out[r[starts]] += np.add.reduceat(weights[order, None] * dense[cols[order]], starts, axis=0)
