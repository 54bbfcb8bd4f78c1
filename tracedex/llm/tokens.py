"""Token ids of whole texts with the public tokenizers (never trained here)."""

from __future__ import annotations

import json
import unicodedata

import numpy as np

#: Chunks that a cache generation holds; two generations bound a worker's memory.
CACHE = 200_000
#: Letters below this code point have the same class and lower case in every library used here.
PLAIN = "ɐ"


def byte_letters() -> dict[str, int]:
    """The printable letter that byte-level vocabularies write for each byte, read backwards."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class WordIds:
    """Ids of single words, merged by tiktoken's core on the word vocabulary's merge ranks.

    A word's last byte carries the end mark, written here as the byte 0xFF, which UTF-8 never has; joining it
    comes before any merge. The words' ids are those of the `tokenizers` library, at a fraction of its cost a call."""

    def __init__(self, path: str):
        import tiktoken

        with open(path) as f:
            model = json.load(f)["model"]
        mark, letters = model["end_of_word_suffix"], byte_letters()

        def raw(token: str) -> bytes:
            body, end = (token[: -len(mark)], b"\xff") if token.endswith(mark) else (token, b"")
            return bytes(letters[c] for c in body) + end

        ranks = {bytes([b, 255]): b for b in range(256)} | {bytes([b]): 256 + b for b in range(256)}
        for i, pair in enumerate(model["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            ranks.setdefault(raw(a) + raw(b), 512 + i)
        vocab = {raw(t): i for t, i in model["vocab"].items() if not t.startswith("<|")}
        self.ids = np.zeros(512 + len(model["merges"]), np.int64)
        for token, rank in ranks.items():
            self.ids[rank] = vocab.get(token, 0)
        self.core = tiktoken.Encoding("words", pat_str=".", mergeable_ranks=ranks, special_tokens={})._core_bpe

    def __call__(self, word: str) -> list[int]:
        """Ranks of the word's parts; `ids` has the id of each rank."""
        return self.core.encode_single_piece(word.encode() + b"\xff")


class ChunkIds(dict):
    """Little-endian ids of the chunks between spaces, encoded on first use.

    The word tokenizer drops white space before it splits words, and neither its normaliser nor its split
    reaches over a space or a line feed, so chunks can be encoded apart and joined. Each chunk is then
    encoded once a worker, not once an occurrence. Chunks of plain Latin letters and signs go through `WordIds`, all
    others through the tokenizer itself."""

    def __init__(self, path: str, kind: str = "<u4"):
        super().__init__()
        import regex
        from tokenizers import Tokenizer

        self.one: dict[str, bytes] = {}  # signs and digits

        self.older: dict[str, bytes] = {}
        self.tokenizer, self.kind, self.words = Tokenizer.from_file(path), kind, WordIds(path)
        self.bytes = [np.array([i], kind).tobytes() for i in self.words.ids]
        with open(path) as f:
            self.split = regex.compile(json.load(f)["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]).findall

    def __missing__(self, chunk: str) -> bytes:
        ids = self.older.get(chunk)
        if ids is None:
            ids = self.encode(chunk)
        if len(self) >= CACHE:
            self.older = dict(self)
            self.clear()
        if len(chunk) < 64:
            self[chunk] = ids
        return ids

    def encode(self, chunk: str) -> bytes:
        if chunk and max(chunk) < PLAIN and "<|" not in chunk and "İ" not in chunk:
            low = (chunk if chunk.isascii() else unicodedata.normalize("NFC", chunk)).lower()
            if low.isalpha():
                return self.word(low)
            return b"".join([self.get(w) or self.word(w) for w in self.split(low)])
        return np.array(self.tokenizer.encode(chunk, add_special_tokens=False).ids, self.kind).tobytes()

    def word(self, low: str) -> bytes:
        """Ids of one lower-cased word or sign; short ones are kept for good."""
        ids = self.one.get(low)
        if ids is None:
            ids = b"".join([self.bytes[r] for r in self.words(low)])
            if len(low) < 4 and len(self.one) < 50_000:
                self.one[low] = ids
        return ids

    def ids(self, text: str | None) -> bytes:
        return b"".join(map(self.__getitem__, text.replace("\n", " ").split(" "))) if text else b""


_OPEN: dict[tuple[str, str], ChunkIds] = {}


def chunk_ids(path: str, kind: str = "<u4") -> ChunkIds:
    """One cache a worker process, kept from task to task."""
    if (path, kind) not in _OPEN:
        _OPEN[path, kind] = ChunkIds(path, kind)
    return _OPEN[path, kind]


def word_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")
