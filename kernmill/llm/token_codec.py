"""Token ids of whole texts by a public tokenizer file, worked out once per different piece.

The file's splitting never joins text across blanks, so a text's ids are the
ids of its blank-separated pieces in order. Texts are cut and their pieces
numbered by Arrow, each different piece of a batch is looked up once, and a
worker remembers pieces in two generations of bounded size: what is in use
survives, the rest is encoded anew when it comes again.
"""

from __future__ import annotations

import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

GENERATION = 100_000
MARK = "\x01"
GROUP = 64
_WORD = re.compile("[a-zà-öø-ÿ]+").fullmatch


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Codec:
    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        (self.mark,) = self._whole(MARK)
        # Latin letters in lower case are one unit that nothing folds or splits, so their ids need the model alone
        self.letters = Tokenizer(self.tokenizer.model)
        self.letters.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        names = self.tokenizer.get_vocab()
        self.closes = np.zeros(max(names.values()) + 1, dtype=bool)
        self.closes[[i for name, i in names.items() if name.endswith("</w>")]] = True

    def _whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _raw(self, text: str) -> bytes:
        return np.array(self._whole(text), dtype="<u2").tobytes()

    def _encode(self, tokenizer, pieces: list[str], between: str):
        groups = [pieces[i : i + GROUP] for i in range(0, len(pieces), GROUP)]
        for group, e in zip(groups, tokenizer.encode_batch_fast([between.join([*g, ""]) for g in groups], add_special_tokens=False)):
            yield group, np.array(e.ids, dtype="<u2")

    def _cut(self, group: list[str], ids: np.ndarray, ends: np.ndarray, skip: int) -> None:
        raw, at = ids.tobytes(), 0
        for s, stop in zip(group, ends.tolist()):
            self.young[s] = raw[2 * at : 2 * stop]
            at = stop + skip

    def _learn(self, fresh: list[str]) -> None:
        """Encode new pieces. Latin words in lower case go to the model alone; others to the whole tokenizer, many to
        a call with a mark between them, and those that hold the mark one by one."""
        words = [p for p in fresh if _WORD(p)]
        rest = [p for p in fresh if not _WORD(p)] if len(words) < len(fresh) else []
        for group, ids in self._encode(self.letters, words, " "):
            self._cut(group, ids, np.flatnonzero(self.closes[ids]) + 1, 0)
        for group, ids in self._encode(self.tokenizer, [s for s in rest if MARK not in s], f" {MARK} "):
            self._cut(group, ids, np.flatnonzero(ids == self.mark), 1)
        for s in rest:
            if MARK in s:
                self.young[s] = self._raw(s)

    def _ids_of(self, pieces: list[str]) -> list[bytes]:
        if len(self.young) > GENERATION:
            self.old, self.young = self.young, {}
        self.young[""] = b""
        out = list(map(self.young.get, pieces))
        absent = [i for i, v in enumerate(out) if v is None]
        names = [pieces[i] for i in absent]
        before = list(map(self.old.get, names))
        self.young.update((p, v) for p, v in zip(names, before) if v is not None)
        self._learn([p for p, v in zip(names, before) if v is None])
        for i, v in zip(absent, map(self.young.__getitem__, names)):
            out[i] = v
        return out

    def encode(self, texts: pa.Array | list[str | None]) -> list[np.ndarray]:
        """uint16 ids (the vocabulary is smaller than 65,536) of each text; null counts as empty.

        Where it cannot change the ids, case is folded and a stop or comma that
        closes a word set apart first, so that fewer pieces differ.
        """
        column = pc.fill_null(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()), "")
        for blank in "\n\t\r":
            column = pc.replace_substring(column, blank, " ")
        plain = pc.replace_substring_regex(pc.utf8_lower(column), r"([a-zà-öø-ÿ])([.,])( |$)", r"\1 \2\3")
        column = pc.if_else(pc.match_substring_regex(column, r"[^\x{00}-\x{ff}]|<"), column, plain)
        rows = pc.split_pattern(column, " ")
        coded = rows.flatten().dictionary_encode()
        blobs = self._ids_of(coded.dictionary.to_pylist())
        known = np.frombuffer(b"".join(blobs), dtype="<u2")
        sizes = np.fromiter(map(len, blobs), dtype=np.int64, count=len(blobs)) // 2
        starts = np.cumsum(sizes) - sizes
        which = coded.indices.to_numpy(zero_copy_only=False)
        each = sizes[which]
        ends = np.concatenate(([0], np.cumsum(each)))
        flat = known[np.repeat(starts[which] - ends[:-1], each) + np.arange(ends[-1])]
        stops = ends[np.concatenate(([0], np.cumsum(pc.list_value_length(rows).to_numpy(zero_copy_only=False))))]
        return [flat[a:b] for a, b in zip(stops[:-1].tolist(), stops[1:].tolist())]


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    """One per worker and file."""
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]
