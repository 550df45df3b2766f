"""Byte-pair token ids of whole texts, each distinct chunk encoded once."""

from __future__ import annotations

import base64

import numpy as np
import pyarrow as pa

from .bytescan import byte_class

#: The splitting pattern always starts a piece at a space that one of these bytes follows:
#: printable ASCII, and the lead byte of U+00C0 to U+00FF, none of which is white space.
_AFTER_SPACE = byte_class(bytes([*range(0x21, 0x7F), 0xC3]))


#: The vocabulary's one special token: where a text has this string, it is one id.
SPECIAL, SPECIAL_ID = b"<|endoftext|>", 50256


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_pair_encoder(path: str, pattern: str | None = None):
    """The tiktoken encoder of a rank file; made once in each Python worker."""
    import tiktoken

    made = tiktoken.__dict__.setdefault("_encoders_by_path", {})
    if path not in made:
        if pattern is None:
            import public_tokenizers

            pattern = public_tokenizers.PATTERN
        with open(path, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in lines)}
        made[path] = tiktoken.Encoding(path, pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    return made[path]


class ChunkEncoder:
    """Ids of many texts at once. The special token's string is its one id, and what is on either side of it is encoded by itself."""

    def __init__(self, path: str):
        coder = byte_pair_encoder(path)
        self.encode = coder.encode_ordinary
        self.width = np.fromiter((len(coder.decode_single_token_bytes(i)) for i in range(coder.n_vocab)), np.int64, coder.n_vocab)

    def __call__(self, raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all rows, number of ids of each row)."""
        rows = len(offs) - 1
        if not len(raw):
            return np.zeros(0, np.uint32), np.zeros(rows, np.int64)
        cut = np.zeros(len(raw), bool)
        cut[:-1] = (raw[:-1] == 0x20) & _AFTER_SPACE[raw[1:]]
        cut[offs[1:][offs[1:] > 0] - 1] = False  # what follows a row's last byte is another row's
        for row in self._special_rows(raw, offs):
            cut[offs[row] : offs[row + 1]] = False
        loose = np.unique(offs[:-1][offs[:-1] < len(raw)])
        loose = loose[~cut[loose]]  # rows that don't start with such a space: each by itself
        cut[loose] = True
        starts = np.flatnonzero(cut)
        bounds = np.append(starts, len(raw))
        chunks = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(bounds), pa.py_buffer(np.ascontiguousarray(raw))])
        alone = np.searchsorted(starts, loose)
        keep = np.ones(len(starts), bool)
        keep[alone] = False
        coded = chunks.filter(pa.array(keep)).dictionary_encode()
        words = coded.dictionary
        _, word_offs, data = words.buffers()
        word_offs = np.frombuffer(word_offs, np.int64, len(words) + 1, words.offset * 8)
        flat = self._array(bytes(data)[word_offs[0] : word_offs[-1]] if len(words) else b"")
        ends_of = np.searchsorted(np.append(0, np.cumsum(self.width[flat])), word_offs - word_offs[0])
        parts, heads, lens = [flat], np.empty(len(starts), np.int64), np.empty(len(starts), np.int64)
        which = coded.indices.to_numpy(zero_copy_only=False)
        heads[keep], lens[keep] = ends_of[:-1][which], np.diff(ends_of)[which]
        at = len(flat)
        for i in alone.tolist():
            own = self._array(raw[bounds[i] : bounds[i + 1]].tobytes())
            parts.append(own)
            heads[i], lens[i] = at, len(own)
            at += len(own)
        flat = np.concatenate(parts)
        ends = np.cumsum(lens)
        ids = flat[np.repeat(heads - (ends - lens), lens) + np.arange(int(ends[-1]))]
        return ids, np.diff(np.append(0, ends)[np.searchsorted(starts, offs)])

    def _special_rows(self, raw: np.ndarray, offs: np.ndarray) -> list[int]:
        """Rows that hold the special token's string; they are encoded whole."""
        data, found = raw.tobytes(), set()
        at = data.find(SPECIAL)
        while at >= 0:
            row = int(np.searchsorted(offs, at, "right")) - 1
            if at + len(SPECIAL) <= offs[row + 1]:
                found.add(row)
            at = data.find(SPECIAL, at + 1)
        return sorted(found)

    def _array(self, text: bytes) -> np.ndarray:
        ids: list[int] = []
        for i, part in enumerate(text.split(SPECIAL)):
            ids += [SPECIAL_ID] * (i > 0)
            ids += self.encode(part.decode())
        return np.array(ids, np.uint32)
