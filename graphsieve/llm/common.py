"""What the operators of this subpackage share."""

from __future__ import annotations

import gc
import re
import sys
import types
from array import array

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsieve.functions.storage import drop_path, materialize, new_path, shared_dir  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str) -> str:
    """Place of a public tokenizer's file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def worker_kept(key, make):
    """What a Python worker keeps from task to task: one tokenizer with its memory, or one hasher; never results.

    Workers outlive stages, so what the stage before kept goes when another asks.
    """
    kept = sys.modules.setdefault("graphsieve_worker_state", types.ModuleType("graphsieve_worker_state")).__dict__.setdefault("kept", {})
    if key not in kept:
        kept.clear()
        kept[key] = make()
    return kept[key]


def id_crc(column: str = "doc_id") -> Column:
    """crc32 of an id as text; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary"))


def utf8(column) -> list[bytes]:
    """Arrow strings as bytes; null is empty."""
    import pyarrow as pa

    return column.cast(pa.large_binary()).fill_null(b"").to_pylist()


class Recent:
    """A bounded memory in two generations: entries that are asked for again outlive the older generation."""

    def __init__(self, limit: int):
        self.limit, self.now, self.old = limit, {}, {}

    def turn(self) -> None:
        """Starts a new generation when this one is full."""
        if len(self.now) > self.limit:
            self.old, self.now = self.now, {}

    def missing(self, keys: set) -> set:
        """Keys that neither generation holds; of the others all are in ``now`` afterwards."""
        new = keys.difference(self.now)
        if new and self.old:
            gone = new.difference(self.old)
            self.now.update([(k, self.old[k]) for k in new.difference(gone)])
            new = gone
        return new


class PieceEncoder:
    """Ids by the tokenizers library, remembered by word.

    A text falls into chunks at places that no token can cross, so the ids of a text are those of its chunks in
    order. Chunks repeat; each distinct one is encoded once and kept as little-endian unsigned 32-bit ids. kind
    "byte": a chunk is a space with the run of other characters behind it, if neither end of the run is white space
    (other texts are cut where a single space stands between two characters that are not white space). kind "word":
    white space separates and is dropped. A new chunk falls into the pieces of the tokenizer's pattern, and only pieces never seen are
    given to the tokenizer's model. Operators (``get``) map the text of an added token to its id, as the library does by default;
    texts that hold one go to it whole. ``led`` holds what follows a space, ``bare`` what does not; both are bounded.
    """

    #: Texts held in a generation; words alone (kind "word") cost less to encode anew than operator 7's executors have memory for.
    LED, BARE, WORDS = 600_000, 100_000, 300_000
    BYTE = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
    WORD = r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+"

    def __init__(self, path: str, kind: str, added: bool = False):
        import json
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import regex
        from tokenizers import Tokenizer

        self.kind, self.tokenizer = kind, Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        # the model alone, for pieces that are already cut, folded and written in its alphabet of bytes
        with open(path, encoding="utf-8") as f:
            given = json.load(f)
        bare = given | {"normalizer": None, "pre_tokenizer": None, "post_processor": None, "added_tokens": []}
        self.model = Tokenizer.from_str(json.dumps(bare))
        self.markers = [t["content"] for t in given["added_tokens"]] if added else []
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        self.alphabet = dict(zip(plain, plain)) | {b: 256 + k for k, b in enumerate(b for b in range(256) if b not in set(plain))}
        self.led = Recent(self.LED if kind == "byte" else self.WORDS)
        self.bare = self.led if kind == "word" else Recent(self.BARE)
        self.pattern = regex.compile(self.BYTE if kind == "byte" else self.WORD)
        #: beyond these, case folding and classes are left to the tokenizer
        self.foreign = re.compile("[^\x00-\x1b\x20-\x7f\xa1-\u017f]|\u0130")
        self.cut = re.compile(r"(?<=\S) (?=\S)")

    @classmethod
    def get(cls, path: str, kind: str) -> PieceEncoder:
        gc.set_threshold(200_000, 50, 1000)  # the memories hold no cycles, but many objects
        return worker_kept(("encoder", path, kind), lambda: cls(path, kind, added=True))

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _fill(self, held: Recent, keys: set, lead: str) -> None:
        """Gives the pieces ``lead + key`` that are new to the model."""
        new = list(held.missing(keys))
        if new:
            table = self.alphabet
            start = lead.translate(table)  # ASCII letters are their own signs in the alphabet
            coded = [start + k if k.isascii() and k.isalpha() else (lead + k).encode().decode("latin-1").translate(table) for k in new]
            held.now.update(zip(new, [array("I", e.ids).tobytes() for e in self.model.encode_batch_fast(coded, add_special_tokens=False)]))

    def _learn(self, chunks: set, lead: str) -> None:
        """Makes ``now`` hold the ids of new chunks: from a piece alone, or from the pieces that they fall into."""
        single, several, foreign, fold = set(), {}, [], self.kind == "word"
        held = self.led if lead or fold else self.bare
        led, bare = single, set()
        for c in chunks:
            if not (c.isascii() and c.isalpha()) and self.foreign.search(c):
                foreign.append(c)
                continue
            text = c.lower() if fold else c
            if c.isalpha():
                if text is c or text == c:
                    single.add(c)
                else:
                    several[c] = ((text, True),)
            elif c and c[-1] in _MARKS and c[:-1].isalpha():
                several[c] = ((text[:-1], True), (c[-1], False))
            else:
                n = len(lead)
                found = self.pattern.findall(lead + text) if text or lead else []
                several[c] = tuple((p[n:], True) if k == 0 and p[:n] == lead else (p, False) for k, p in enumerate(found))
        for ps in several.values():
            for p, first in ps:
                (led if first else bare).add(p)
        other = self.bare if held is not self.bare else held
        self._fill(held, led, lead)
        self._fill(other, bare, "")
        a, b = held.now, other.now
        ids = {c: b"".join([a[p] if first else b[p] for p, first in ps]) for c, ps in several.items()}
        held.now.update(ids)
        if foreign:
            held.now.update(zip(foreign, self._whole([lead + c for c in foreign])))

    def encode(self, text: str) -> bytes:
        """Ids of a text, as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        for marker in self.markers:
            if marker in text:
                self.tokenizer.encode_special_tokens = False  # the library's default
                ids = self.tokenizer.encode(text, add_special_tokens=False).ids
                self.tokenizer.encode_special_tokens = True
                return array("I", ids).tobytes()
        self.led.turn()
        self.bare.turn()
        if self.kind == "word":
            return self._join(self.led, text.replace("\n", " ").split(" "), "")
        first, *rest = text.split(" ")
        if first and not first[-1].isspace():
            ids = self._join(self.led, rest, " ", strict=True)
            if ids is not None:
                return self._join(self.bare, [first], "") + ids
        chunks = self.cut.split(text)
        texts = [chunks[0], *(" " + c for c in chunks[1:])]
        ids = dict(zip(new := list(dict.fromkeys(texts)), self._whole(new)))
        return b"".join(map(ids.__getitem__, texts))

    def _join(self, held: Recent, chunks: list[str], lead: str, strict: bool = False) -> bytes | None:
        got = list(map(held.now.get, chunks))
        try:
            return b"".join(got)
        except TypeError:  # some are not in ``now``
            new = held.missing({c for c, ids in zip(chunks, got) if ids is None})
        if new:
            if strict and any(not c or c[0].isspace() or c[-1].isspace() for c in new):
                return None
            self._learn(new, lead)
        return b"".join(map(held.now.__getitem__, chunks))


_MARKS = frozenset(".,;:!?")
