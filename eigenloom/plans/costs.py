"""Cost formulas of the planner and the ledger, in bytes."""

from __future__ import annotations


def block(n: int, width: int) -> int:
    return 8 * n * width


def expansion(n: int, width: int, held: int, matrix_bytes: int, passes: int = 2, products: int = 1) -> tuple[int, int]:
    """(read, written) of one step with `held` vectors: the matrix once per product, and the subspace twice per pass."""
    return products * matrix_bytes + 2 * passes * block(n, held), block(n, width)


def restart(n: int, held: int, kept: int) -> tuple[int, int]:
    return block(n, held), block(n, kept)


def resident(n: int, width: int) -> int:
    """Two narrow blocks, however many values are wanted."""
    return 2 * block(n, width)


def solve(n: int, width: int, limit: int, kept: int, matrix_bytes: int, restarts: int, products: int = 1) -> tuple[int, int]:
    """(read, written) of a whole solve."""
    read = written = 0
    for r in range(restarts + 1):
        for q in range(kept + width if r else width, limit + 1, width):
            step = expansion(n, width, q, matrix_bytes, 2, products)
            read, written = read + step[0], written + step[1]
        if r < restarts:
            step = restart(n, limit, kept)
            read, written = read + step[0], written + step[1]
    return read, written


def stored_solve(n: int, steps: list[tuple[str, int, int]], matrix_bytes: int, start_width: int, cached: bool = True) -> tuple[int, int]:
    """(read, written) of a solve by the bucketed store from its steps ('expand', columns held, block width) and ('restart', columns held, columns kept).

    A step reads the matrix and the newest block, and the held columns twice, with the cache of the recent block, of which the symmetric operator's product is an array, and else three times;
    it writes one block, and without the cache the product too, which each scan reads again. The start writes a random block and its normalised form, of which the first is read once.
    """
    read, written = block(n, start_width), 2 * block(n, start_width)
    for kind, held, other in steps:
        if kind == "expand":
            read += matrix_bytes + block(n, other) + (2 if cached else 3) * block(n, held) + (0 if cached else 3 * block(n, other))
            written += block(n, other) * (1 if cached else 2)
        else:
            read, written = read + block(n, held), written + block(n, other)
    return read, written
