"""Block compressors behind one call, software alone or two lanes side by side."""

from __future__ import annotations

import gzip
import importlib
import importlib.util
from typing import Protocol


class BlockCodec(Protocol):
    """Anything that turns the bytes of a block into a standard gzip member."""

    name: str

    def compress(self, raw: bytes, block: int = 0) -> bytes: ...


class GzipCodec:
    """Software lane."""

    def __init__(self, level: int = 6):
        self.level, self.name = level, f"gzip{level}"

    def compress(self, raw: bytes, block: int = 0) -> bytes:
        return gzip.compress(raw, self.level, mtime=0)


class FastGzipCodec(GzipCodec):
    """Stands for an accelerator where no accelerated library is installed: the lowest level of the same format."""

    def __init__(self):
        super().__init__(1)
        self.name = "fast"


class AcceleratedCodec:
    """A library with zlib's calls that the machine offers, such as a hardware-backed one."""

    def __init__(self, module: str):
        self.lib, self.name = importlib.import_module(module), module

    def compress(self, raw: bytes, block: int = 0) -> bytes:
        return self.lib.compress(raw)


class DualLane:
    """Hands every ``share``-th block, by its number, to the slow lane and the rest to the fast one; readers need not know."""

    def __init__(self, fast: BlockCodec, slow: BlockCodec, share: int = 2):
        self.fast, self.slow, self.share, self.name = fast, slow, share, f"{fast.name}+{slow.name}"

    def compress(self, raw: bytes, block: int = 0) -> bytes:
        return (self.slow if block % self.share == self.share - 1 else self.fast).compress(raw, block)


#: Public modules whose ``compress`` gives gzip members faster than zlib, best first.
ACCELERATORS = ("isal.igzip", "zlib_ng.gzip_ng")


def accelerator() -> BlockCodec | None:
    """The first accelerator library that this process can load; none is the usual case."""
    for module in ACCELERATORS:
        try:
            if importlib.util.find_spec(module) is not None:
                return AcceleratedCodec(module)
        except ModuleNotFoundError:
            continue
    return None


def detect_codecs() -> dict[str, BlockCodec]:
    """The codecs of this process: software always; the fast lane is an accelerator if one loads, else a lower level."""
    found: dict[str, BlockCodec] = {"software": GzipCodec(), "fast": accelerator() or FastGzipCodec()}
    found["dual"] = DualLane(found["fast"], found["software"])
    return found


def codec(name: str) -> BlockCodec:
    return detect_codecs()[name]
