"""All tile formats by name."""

from __future__ import annotations

from .base import Format
from .grammar import PairGrammar
from .pieces import Biclique, ColGroup
from .plain import DEFLATE, LZMA, Csr, Dense, EdgeList
from .quadbits import BlockTree, QuadBits
from .refcopy import RefCopy

FORMATS: dict[str, Format] = {f.name: f for f in (EdgeList(), Csr(), Dense(), DEFLATE, LZMA, QuadBits(), BlockTree(), *map(PairGrammar, ("w32", "packed", "folded")), *map(RefCopy, ("prefix", "stream")), Biclique(), ColGroup())}
#: The compressed formats whose sizes, times and energies are compared, largest first on web-like matrices.
COMPARED = ("pg_w32", "pg_packed", "pg_folded", "quadbits", "refcopy_stream")
