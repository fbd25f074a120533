"""Parameters of a neighbour sketch."""

from __future__ import annotations

from dataclasses import asdict, dataclass

PRIME = 2147483647  # 2**31 - 1: products of two residues stay below 2**62
FAMILIES = ("minhash", "onebit_minhash", "signed_projection", "euclidean_grid", "bit_sample")
SHARINGS = ("cell", "row", "rep")
MIXERS = ("portable", "murmur3", "xxhash64")
MEASUREMENTS = ("cms", "signed", "bernoulli")


@dataclass(frozen=True)
class SketchParams:
    """A grid of rows x cols cells with reps collision arrays each. Two sketches
    merge only if their parameters are equal."""

    rows: int
    cols: int
    reps: int
    hashes: int = 1
    buckets: int | None = 100  # None: no re-hash; code_range ** hashes slots
    family: str = "minhash"
    seed: int = 42
    sharing: str = "cell"
    mixer: str = "portable"
    measurement: str = "cms"
    width: float = 1.0  # of a cell of the Euclidean grid

    def __post_init__(self):
        if min(self.rows, self.cols, self.reps, self.hashes) < 1 or (self.buckets is not None and self.buckets < 1):
            raise ValueError("all sizes of a sketch are positive")
        for value, known in ((self.family, FAMILIES), (self.sharing, SHARINGS), (self.mixer, MIXERS), (self.measurement, MEASUREMENTS)):
            if value not in known:
                raise ValueError(f"{value!r} is not one of {known}")
        if self.buckets is None and self.code_range is None:
            raise ValueError(f"{self.family} has no bounded range: give a number of buckets")
        if self.rows * self.cols * self.reps * self.slots >= 1 << 62:
            raise ValueError("packed coordinates would not fit")

    @property
    def code_range(self) -> int | None:
        """The range of one hash value, where it is small enough to do without a re-hash."""
        return {"onebit_minhash": 2, "signed_projection": 2, "bit_sample": 2}.get(self.family)

    @property
    def slots(self) -> int:
        """Length of one collision array."""
        return self.buckets if self.buckets is not None else self.code_range**self.hashes

    @property
    def arrays(self) -> int:
        return self.rows * self.cols * self.reps

    @property
    def counters(self) -> int:
        return self.arrays * self.slots

    def shared(self, row: int, col: int, rep: int) -> tuple[int, int, int]:
        """The coordinates that own the hash functions of this array."""
        if self.sharing == "cell":
            return row, col, rep
        return (row, 0, rep) if self.sharing == "row" else (0, 0, rep)

    def as_dict(self) -> dict:
        return asdict(self)
