"""What a dictionary is built with. Stored in its manifest and checked when it is opened or probed."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, fields

FORMAT = 1
METHODS = ("dense", "sparse", "one_level", "two_level", "shared_inverse", "global_sparse")


@dataclass(frozen=True)
class DictSpec:
    """k: bits of a value. method: see METHODS.

    c: variables beyond the number of equations. field: binary (0/1 coefficients, k right sides at once) or full (GF(2^k)).
    kind: rows of cells (dense, sparse, logsparse, local). t: non-zeros of sparse rows; slack: variables per equation of the
    sparse method. digest: xxhash, md5 or identity. hashing: direct, or table (near-uniform from a pairwise independent index).
    solver: eliminate, or listed for cells whose coefficients take 16 bits; structured, krylov (single vectors) or block for sparse systems. most_single,
    most_global: keys that one dense and one sparse system may have, as they are solved by one task; more are refused, or where this is
    None go to several systems by a hash of the keys. on_conflict: error, min or max for keys with several values. on_null: error or drop for null keys. bad_share: keys that overfull buckets may hold before
    the bucket hash is redrawn, as a share of all; None: 1 / log^2 n. pre_dedupe: whether equal keys meet in a partial aggregate
    before they move to their bucket; None: if the count of rows and distinct keys says that many repeat, or is left out.
    """

    k: int
    method: str = "two_level"
    c: int = 0
    field: str = "binary"
    kind: str = "dense"
    t: int | None = None
    window: int = 16
    slack: float | None = None
    replace: bool = False
    allow_even: bool = False
    digest: str = "xxhash"
    hashing: str = "direct"
    solver: str = "eliminate"
    on_conflict: str = "error"
    on_null: str = "error"
    seed: int = 1
    bucket_mean: int = 4096
    bucket_cap: int | None = None
    cell_mean: float = 40.0
    cell_cap: int = 64
    seed_tries: int = 64
    split_tries: int = 64
    most_single: int | None = None
    most_global: int | None = None
    table_len: int | None = None
    n_funcs: int | None = None
    bad_share: float | None = None
    pre_dedupe: bool | None = None
    membership: bool = False
    strict_empty: bool = True
    key_types: tuple[str, ...] = ()

    def __post_init__(self):
        top = 16 if self.field == "full" else 32
        if not 1 <= self.k <= top:
            raise ValueError(f"k must be from 1 to {top}")
        if self.method not in METHODS:
            raise ValueError(f"method must be one of {METHODS}")
        if self.on_conflict not in ("error", "min", "max") or self.on_null not in ("error", "drop"):
            raise ValueError("on_conflict is error, min or max; on_null is error or drop")
        if self.method in ("two_level", "shared_inverse") and self.cell_cap + self.c > 64:
            raise ValueError("a cell holds at most 64 variables")
        if self.solver == "listed" and (self.c or self.cell_cap**2 * (self.k if self.field == "full" else 1) > 16):
            raise ValueError("lists of all matrices are made for square systems whose coefficients take at most 16 bits")
        if self.method == "global_sparse" and self.t is not None and self.t % 2 == 0 and not self.allow_even:
            raise ValueError("rows of a square system need an odd number of places: with an even one it is always singular")
        if self.method == "sparse" and (self.t or 3) < 3 and (self.slack or 0) < 2:
            raise ValueError("rows of fewer than 3 places need slack of at least 2")
        if self.hashing == "table" and self.method != "two_level":
            raise ValueError("table hashing belongs to the two-level method")

    @property
    def by_variable(self) -> bool:
        """Whether cells keep variable after variable instead of plane after plane, so that a window of a local row is two words at most."""
        return self.kind == "local" and self.field == "binary" and self.method == "two_level" and self.window * self.k <= 64

    @property
    def cap(self) -> int:
        return self.bucket_cap if self.bucket_cap is not None else 2 * self.bucket_mean

    def to_json(self) -> str:
        return json.dumps(asdict(self) | {"format": FORMAT})

    @staticmethod
    def from_json(text: str) -> DictSpec:
        d = json.loads(text)
        if d.pop("format", None) != FORMAT:
            raise ValueError("the store has another format version")
        known = {f.name for f in fields(DictSpec)}
        return DictSpec(**{k: tuple(v) if isinstance(v, list) else v for k, v in d.items() if k in known})


def practical(k: int, **more) -> DictSpec:
    """Defaults for real sizes: cells of mean 40 in one machine word."""
    return DictSpec(k=k, **more)
