"""Token ids of whole texts by a public tokenizer, piecewise: a text is the concatenation of chunks that the
tokenizer never joins, and the ids of frequent chunks are remembered in each worker.

Chunks end before a single space that stands between two characters which are not white space. Both vocabularies
start a new pre-token there, so ids of chunks laid end to end are ids of the text; texts with other white space
beside a space go through the tokenizer whole. Arrow splits a batch and numbers its distinct chunks, the tokenizer
sees those that are new, and numpy lays out the ids.
"""

from __future__ import annotations

import os
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Chunks remembered by one worker, in each of two generations; a full one replaces the older.
REMEMBERED = 220_000
#: Longest chunk worth remembering, in characters.
LONGEST = 40
#: Bytes of text that are laid out together.
PART = 6_000_000
#: Marks the first chunk of a text, which has no space before it; texts that hold it go whole.
FIRST = "\x02"
#: Marks punctuation (no apostrophes) between a letter and a space, a pre-token of its own in both vocabularies.
MARK = "\x01"
ENDING = r"([A-Za-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{FF}])([!-&(-/:-@\[-`{-~]+) "


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class ChunkEncoder:
    """Ids of texts, equal to encoding each whole text with the tokenizers library."""

    def __init__(self, path: str, fold_ascii: bool = False):
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.whole = Tokenizer.from_file(path)
        self.whole.encode_special_tokens = True
        self.lengths = np.zeros(self.whole.get_vocab_size(), np.int64)  # bytes of each token
        for token, i in self.whole.get_vocab().items():
            self.lengths[i] = len(token.removesuffix("</w>"))
        self.fold = fold_ascii
        self.letters = None
        if fold_ascii:  # words of lower-case letters need no normalizing and are pre-tokens as they are
            self.letters = Tokenizer.from_file(path)
            self.letters.normalizer = normalizers.Sequence([])
            self.letters.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.Split(" ", "removed"), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        self.seen: dict[str, bytes | None] = {FIRST: b""}
        self.older: dict[str, bytes | None] = {}

    def encode_whole(self, text: str) -> np.ndarray:
        return np.array(self.whole.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")

    def _encode(self, parts: list[str], tokenizer=None) -> list[bytes]:
        """Ids of chunks: they are encoded end to end and told apart by the lengths of their bytes and of the tokens'."""
        out: list[bytes] = []
        for at in range(0, len(parts), 2000):
            some = parts[at : at + 2000]
            ids = np.array((tokenizer or self.whole).encode_batch_fast(["".join(some)], add_special_tokens=False)[0].ids, "<u4")
            texts = ["".join(w.split()) for w in some] if self.fold else some  # this vocabulary drops white space
            ends = np.cumsum(np.fromiter(map(len, map(str.encode, texts)), np.int64, len(some)))
            token_ends = np.cumsum(self.lengths[ids])
            cuts = np.searchsorted(token_ends, ends)
            if len(ids) and token_ends[-1] == ends[-1] and (token_ends[np.minimum(cuts, len(ids) - 1)] == ends).all():
                data, cuts = ids.tobytes(), ((cuts + 1) * 4).tolist()
                out += [data[s:e] for s, e in zip([0, *cuts[:-1]], cuts, strict=True)]
            else:
                out += self._encode_each(some)
        return out

    def _encode_each(self, parts: list[str]) -> list[bytes]:
        """The same one by one: for chunks without a space before them, and where the tokenizer changes letters."""
        return [np.array(e.ids, "<u4").tobytes() for e in self.whole.encode_batch_fast(parts, add_special_tokens=False)]

    def _ids_of(self, chunks: list[str]) -> list[bytes | None]:
        """Ids of distinct chunks; None for those that cannot stand alone."""
        if len(self.seen) > REMEMBERED:
            self.older, self.seen = self.seen, {FIRST: b""}
        seen, older = self.seen, self.older
        new = [w for w in chunks if w not in seen]
        found: dict[str, bytes | None] = {}
        fresh, heads = [], []
        for w in new:
            if w in older:
                seen[w] = older[w]
                continue
            bare = w[:1] in (FIRST, MARK)
            word = w[1:] if bare else w
            if not word or word != word.strip():
                found[w] = None
            else:
                (heads if bare else fresh).append(w)
        if self.letters is not None:
            plain = [w for w in fresh if w.isalpha() and w.islower() and (w.isascii() or unicodedata.is_normalized("NFC", w))]
            found.update(zip(plain, self._encode([" " + w for w in plain], self.letters), strict=True))
            fresh = [w for w in fresh if w not in found]
        found.update(zip(fresh, self._encode([" " + w for w in fresh]), strict=True))
        if heads:
            found.update(zip(heads, self._encode_each([w[1:] for w in heads]), strict=True))
        seen.update((w, v) for w, v in found.items() if len(w) <= LONGEST)
        return [seen[w] if w in seen else found[w] for w in chunks]

    def encode_column(self, column: pa.Array, end_id: int) -> list[np.ndarray]:
        """Ids of each text with the end id after them, as unsigned 32-bit arrays; nulls are empty."""
        column = pc.fill_null(column.cast(pa.large_utf8()), "")
        sizes, out, at = np.cumsum(pc.binary_length(column).to_numpy(zero_copy_only=False)), [], 0
        while at < len(column):
            done = sizes[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(sizes, done + PART)))
            out += self._part(column.slice(at, to - at), end_id)
            at = to
        return out

    def encode_many(self, texts: list[str], end_id: int = 0) -> list[np.ndarray]:
        return self.encode_column(pa.array(texts, pa.large_utf8()), end_id)

    def _part(self, column: pa.Array, end_id: int) -> list[np.ndarray]:
        texts = pc.ascii_lower(column) if self.fold else column
        if self.fold:  # white space of any kind only parts words here
            texts = pc.replace_substring(texts, "\n", " ")
        odd = pc.or_(pc.match_substring_regex(texts, f"[{FIRST}{MARK}]"), pc.starts_with(texts, " ")).to_numpy(zero_copy_only=False)
        texts = pc.replace_substring_regex(texts, ENDING, rf"\1 {MARK}\2 ")
        marked = pc.binary_join_element_wise(pa.scalar(FIRST, pa.large_utf8()), texts, pa.scalar("", pa.large_utf8()))
        lists = pc.split_pattern(marked, " ")
        coded = lists.flatten().dictionary_encode()
        index = coded.indices.to_numpy()
        ids = self._ids_of(coded.dictionary.to_pylist())
        ends = np.cumsum(lists.value_lengths().to_numpy())
        unsafe = np.fromiter((v is None for v in ids), bool, len(ids))
        if unsafe.any():
            odd = odd | (np.add.reduceat(unsafe[index], np.r_[0, ends[:-1]]) > 0)
        ids = [v or b"" for v in ids]
        sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        flat = np.frombuffer(b"".join([*ids, np.array([end_id], "<u4").tobytes()]), "<u4")
        sizes = np.r_[sizes, 1]
        first = (np.cumsum(sizes) - sizes).astype(np.int32)
        index = np.insert(index, ends, len(ids))  # the end id is one more chunk of each text
        n = sizes[index]
        upto = np.cumsum(n)
        place = np.repeat(first[index] - (upto - n).astype(np.int32), n)
        place += np.arange(len(place), dtype=np.int32)
        laid = flat[place]
        cuts = upto[ends + np.arange(len(ends))]
        out = [laid[s:e] for s, e in zip(np.r_[0, cuts[:-1]].tolist(), cuts.tolist(), strict=True)]
        for i in np.flatnonzero(odd):
            out[i] = np.r_[self.encode_whole(column[int(i)].as_py()), np.array([end_id], "<u4")].astype("<u4")
        return out


_ENCODERS: dict = {}


def encoder(path: str, fold_ascii: bool = False) -> ChunkEncoder:
    """One encoder for each worker process and vocabulary."""
    key = (path, fold_ascii)
    if key not in _ENCODERS:
        _ENCODERS[key] = ChunkEncoder(path, fold_ascii)
    return _ENCODERS[key]
