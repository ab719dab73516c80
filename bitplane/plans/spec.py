"""What is known about an encoded column, and the manifest of an encoded dataset."""

from __future__ import annotations

import dataclasses
import json

from ..functions import codecs
from ..functions.codecs import Codec

SCOPES = ("none", "block", "file", "global")


@dataclasses.dataclass(frozen=True)
class ColumnSpec:
    """``planes`` holds for the whole dataset; blocks may use fewer.  ``base`` is the literal bias of the scopes none and global."""

    name: str
    codec: Codec
    bias: str = "block"
    planes: int = 1
    base: int = 0
    lo: int | None = None  # ordinals over the dataset, if any value is not null
    hi: int | None = None
    width: str | int = "block"  # block, global, or a fixed number of planes
    has_nulls: bool = True
    bloom: bool = False

    @property
    def literal(self) -> bool:
        return self.bias in ("none", "global")

    def plane(self, j: int) -> str:
        return f"{self.name}__p{j}"

    def header(self, part: str) -> str:
        return f"{self.name}__{part}"


@dataclasses.dataclass(frozen=True)
class Manifest:
    columns: tuple[ColumnSpec, ...]
    block_size: int = 1024
    rows: int | None = None
    files: int | None = None
    exact: bool = True  # whether lo, hi, has_nulls and rows are those of the data

    def __getitem__(self, name: str) -> ColumnSpec:
        return next(c for c in self.columns if c.name == name)

    def __contains__(self, name: str) -> bool:
        return any(c.name == name for c in self.columns)

    def to_json(self) -> str:
        def column(c: ColumnSpec) -> dict:
            d = {f.name: getattr(c, f.name) for f in dataclasses.fields(c) if f.name != "codec"}
            return d | {"codec": type(c.codec).__name__, "options": dataclasses.asdict(c.codec)}

        return json.dumps({"block_size": self.block_size, "rows": self.rows, "files": self.files, "exact": self.exact, "columns": [column(c) for c in self.columns]})

    def open(self) -> Manifest:
        """Of data whose bounds are not known: predicates are decided by block headers alone."""
        free = [dataclasses.replace(c, lo=None, hi=None, has_nulls=True) for c in self.columns]
        return dataclasses.replace(self, columns=tuple(free), rows=None, exact=False)

    def mismatch(self, other: Manifest) -> str | None:
        """Why the two parts' planes do not mean the same; more planes do no harm, as missing ones are empty."""
        if self.block_size != other.block_size:
            return "block sizes differ"
        if [c.name for c in self.columns] != [c.name for c in other.columns]:
            return "columns differ"
        for a, b in zip(self.columns, other.columns):
            for part in ("codec", "bias", "base", "bloom"):
                if getattr(a, part) != getattr(b, part):
                    return f"{a.name}: {part} differs"
        return None

    @staticmethod
    def merged(parts: list[Manifest]) -> Manifest:
        """Of a dataset of several parts: extremes, nulls and rows of all of them."""
        first = parts[0]
        for other in parts[1:]:
            if why := first.mismatch(other):
                raise ValueError(f"the parts were encoded differently: {why}")
        exact = all(p.exact for p in parts)
        cols = []
        for same in zip(*(p.columns for p in parts)):
            lows, highs = [c.lo for c in same if c.lo is not None], [c.hi for c in same if c.hi is not None]
            lo, hi = (min(lows), max(highs)) if exact and lows else (None, None)
            cols.append(dataclasses.replace(same[0], planes=max(c.planes for c in same), lo=lo, hi=hi, has_nulls=not exact or any(c.has_nulls for c in same)))
        rows = sum(p.rows for p in parts) if all(p.rows is not None for p in parts) else None
        return dataclasses.replace(first, columns=tuple(cols), rows=rows, exact=exact)

    @classmethod
    def from_json(cls, text: str) -> Manifest:
        d = json.loads(text)
        out = []
        for c in d["columns"]:
            options = {k: tuple(v) if isinstance(v, list) else v for k, v in c.pop("options").items()}
            out.append(ColumnSpec(codec=getattr(codecs, c.pop("codec"))(**options), **c))
        return cls(tuple(out), d["block_size"], d["rows"], d["files"], d.get("exact", True))
