"""Public tokenizers, opened once in each Python worker.

A word-level memo is kept between the tasks of a worker, in two generations: when the younger has
``MEMO_WORDS`` words it becomes the elder and the former elder is dropped, so frequent words stay and
memory is bounded whatever the corpus.
"""

from __future__ import annotations

import base64
import os
import re

MEMO_WORDS = 300_000
_WORDS = re.compile(r"[^ \t\r\n]+")
_open: dict[tuple[str, str], object] = {}


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(piece): int(rank) for piece, rank in map(bytes.split, lines)}


class _Memo(dict):
    """Word to ids; a missing word is taken from the elder generation or encoded."""

    def __init__(self, encode, elder: dict[str, bytes]):
        super().__init__()
        self._encode, self._elder = encode, elder

    def __missing__(self, word: str) -> bytes:
        found = self._elder.get(word)
        if found is None:
            found = self._encode(word)
        self[word] = found
        return found


class WordMemoEncoder:
    """Ids of a ``tokenizers`` file whose pre-tokenizer drops white space.

    White space never joins two words of such a tokenizer, so a text's ids are its words' ids in
    order.  ``str.split`` takes four controls for white space that the tokenizer does not; texts
    with one of them are split at blanks, tabs and line ends only.

    Words of printable Latin-1 characters, for which lower-casing and NFC are one-to-one, are
    merged by ``tiktoken`` with the ranks of the file's own merges; all others by ``tokenizers``.
    """

    #: The file's split pattern for lower-case Latin-1 words, where its classes are these.
    _LETTERS = "a-z\xaa\xb5\xba\xdf-\xf6\xf8-\xff"
    _DIGITS = "0-9\xb2\xb3\xb9\xbc-\xbe"

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import json

        import tiktoken
        from tokenizers import Tokenizer

        self._tokenizer = Tokenizer.from_file(path)
        self._tokenizer.encode_special_tokens = True
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        end = spec["model"]["end_of_word_suffix"]
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        own = split.replace(r"[\p{L}]", f"[{self._LETTERS}]").replace(r"[\p{N}]", f"[{self._DIGITS}]").replace(r"[^\s\p{L}\p{N}]", f"[^{self._LETTERS}{self._DIGITS}]")
        self._pieces = re.compile(own).findall if "\\" not in own else None
        self._plain = re.compile("[!-~\xa1-\xff]+").fullmatch

        # Byte 255 never occurs in UTF-8: it stands for the end of a word and joins the last byte first.
        letters = byte_letters()

        def raw(token: str) -> bytes:
            ends = token.endswith(end)
            return bytes(letters[c] for c in (token[: -len(end)] if ends else token)) + (b"\xff" if ends else b"")

        merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        order = dict.fromkeys([bytes([b, 255]) for b in range(255)] + [bytes([b]) for b in range(256)] + [raw(a + b) for a, b in merges])
        ids = {raw(t): i for t, i in spec["model"]["vocab"].items() if all(c in letters for c in t.removesuffix(end))}
        self._core = tiktoken.Encoding("merges", pat_str=r"\S+", mergeable_ranks={t: i for i, t in enumerate(order)}, special_tokens={})._core_bpe.encode_single_piece
        self._ids = [ids.get(t, -1).to_bytes(4, "little", signed=True) for t in order]
        self._memo = _Memo(self._encode_word, {})

    def _encode_word(self, word: str) -> bytes:
        if self._pieces and self._plain(word):
            ids, core = self._ids, self._core
            return b"".join([ids[i] for piece in self._pieces(word.lower()) for i in core(piece.encode() + b"\xff")])
        from array import array

        return array("I", self._tokenizer.encode(word, add_special_tokens=False).ids).tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        out = []
        for text in texts:
            if len(self._memo) > MEMO_WORDS:
                self._memo = _Memo(self._encode_word, dict(self._memo))
            odd = "\x1c" in text or "\x1d" in text or "\x1e" in text or "\x1f" in text
            out.append(b"".join(map(self._memo.__getitem__, _WORDS.findall(text) if odd else text.split())))
        return out


def byte_letters() -> dict[str, int]:
    """The usual printable letters for bytes in byte-level vocabularies, as letter: byte."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


def word_memo_encoder(path: str) -> WordMemoEncoder:
    key = ("words", path)
    if key not in _open:
        _open[key] = WordMemoEncoder(path)
    return _open[key]


def rank_file_encoder(path: str):
    """A ``tiktoken`` encoding of a rank file, without special tokens."""
    key = ("ranks", path)
    if key not in _open:
        import public_tokenizers
        import tiktoken

        _open[key] = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=read_ranks(path), special_tokens={})
    return _open[key]


def slices(texts: list[str], chars: int = 400_000):
    """Index ranges of ``texts`` with about ``chars`` characters each (one text at least)."""
    begin = held = 0
    for i, text in enumerate(texts):
        held += len(text)
        if held >= chars:
            yield begin, i + 1
            begin, held = i + 1, 0
    if begin < len(texts):
        yield begin, len(texts)
