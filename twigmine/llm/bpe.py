"""BPE encoding and decoding: merge rounds over one flat array of the symbols of many words.

A round looks up the rank of every adjacent pair by binary search over the sorted pair keys, finds each word's
lowest rank, and merges every pair of that rank in the word, left to right.
"""

from __future__ import annotations

import json
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import StringType, StructField, StructType

from .common import pieces, trim

#: Words kept by a Python worker, about 100 bytes each; when full the memory starts anew.
MOST_KEPT = 200_000
NO_RANK = np.int64(1) << 40


def byte_letters() -> list[str]:
    """Letter of each byte in a byte-level vocabulary: printable bytes stand for themselves, the others follow from 256."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(others)) for b in range(256)]


def load_tables(path: str) -> dict:
    """What the merge rounds need from a tokenizer file of the word-end kind."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model = spec["model"]
    vocab = {t: int(i) for t, i in model["vocab"].items()}
    end = model["end_of_word_suffix"] or ""
    letters = byte_letters()
    pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
    keys = np.array([(vocab[a] << 32) | vocab[b] for a, b in pairs], np.int64)
    made = np.array([vocab[a + b] for a, b in pairs], np.int64)
    order = np.argsort(keys, kind="stable")
    special = {t["content"]: int(t["id"]) for t in spec["added_tokens"]}
    names = [""] * (max([*vocab.values(), *special.values()]) + 1)
    for t, i in [*vocab.items(), *special.items()]:
        names[i] = t
    split = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
    return {"keys": keys[order], "rank": order.astype(np.int64), "made": made[order], "inner": np.array([vocab[c] for c in letters], np.int64), "last": np.array([vocab[c + end] for c in letters], np.int64), "special": special, "names": names, "split": split}


def merge_rounds(words: list[bytes], tables: dict) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all words in one array, and where each word's ids begin (one entry more than words)."""
    sizes = np.array([len(w) for w in words], np.int64)
    first = np.concatenate([[0], np.cumsum(sizes)])
    flat = np.frombuffer(b"".join(words), np.uint8)
    symbols = tables["inner"][flat]
    ends = first[1:][sizes > 0] - 1
    symbols[ends] = tables["last"][flat[ends]]
    owner = np.repeat(np.arange(len(words)), sizes)
    keys, rank, made = tables["keys"], tables["rank"], tables["made"]
    done_symbols, done_owner = [], []
    while len(symbols) > 1:
        same = owner[:-1] == owner[1:]
        key = (symbols[:-1] << 32) | symbols[1:]
        at = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
        hit = same & (keys[at] == key)
        score = np.append(np.where(hit, rank[at], NO_RANK), NO_RANK)
        begin = np.flatnonzero(np.concatenate([[True], ~same]))
        lowest = np.minimum.reduceat(score, begin)
        lengths = np.diff(np.append(begin, len(symbols)))
        active = lowest < NO_RANK
        if not active.all():
            rest = np.repeat(~active, lengths)
            done_symbols.append(symbols[rest])
            done_owner.append(owner[rest])
            keep = ~rest
            symbols, owner, score = symbols[keep], owner[keep], score[keep]
            at = np.append(at, 0)[keep]
            lowest, lengths = lowest[active], lengths[active]
            if not len(symbols):
                break
        else:
            at = np.append(at, 0)
        chosen = np.flatnonzero(score == np.repeat(lowest, lengths))
        # In a run of overlapping pairs (aaa) every second one merges, from the left.
        fresh = np.concatenate([[True], np.diff(chosen) > 1])
        run = np.flatnonzero(fresh)
        inside = np.arange(len(chosen)) - np.repeat(run, np.diff(np.append(run, len(chosen))))
        chosen = chosen[inside % 2 == 0]
        symbols[chosen] = made[at[chosen]]
        left = np.ones(len(symbols), bool)
        left[chosen + 1] = False
        symbols, owner = symbols[left], owner[left]
    done_symbols.append(symbols)
    done_owner.append(owner)
    ids, owner = np.concatenate(done_symbols), np.concatenate(done_owner)
    order = np.argsort(owner, kind="stable")
    return ids[order].astype(np.uint32), np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=len(words)))])


class Encoder:
    """Texts to ids; remembers the words it has met."""

    def __init__(self, tables: dict):
        import regex

        self.tables = tables
        self.words = regex.compile(tables["split"]).findall
        self.special = regex.compile("|".join(map(regex.escape, sorted(tables["special"], key=len, reverse=True)))) if tables["special"] else None
        self.forget()

    def forget(self) -> None:
        self.slot: dict[str, int] = {}
        self.ids, self.first = np.zeros(0, np.uint32), np.zeros(1, np.int64)
        for content, number in self.tables["special"].items():
            self.slot["\0" + content] = len(self.first) - 1
            self.ids = np.append(self.ids, np.uint32(number))
            self.first = np.append(self.first, self.first[-1] + 1)

    def split(self, text: str) -> list[str]:
        # White space becomes one space in the file's rules; the words don't depend on it.
        return self.words(unicodedata.normalize("NFC", text).replace("Σ", "σ").lower())

    def parts(self, text: str) -> list[str]:
        if self.special is None or "<|" not in text:
            return self.split(text)
        out, at = [], 0
        for m in self.special.finditer(text):
            out += self.split(text[at : m.start()])
            out.append("\0" + m[0])
            at = m.end()
        return out + self.split(text[at:])

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian 32-bit ids of each text."""
        if len(self.slot) > MOST_KEPT:
            self.forget()
        slot, new, lists = self.slot, [], []
        for text in texts:
            words = self.parts(text)
            fresh = [w for w in dict.fromkeys(words) if w not in slot]
            slot.update(zip(fresh, range(len(slot), len(slot) + len(fresh))))
            new += fresh
            lists.append(np.fromiter(map(slot.__getitem__, words), np.int64, len(words)))
        if new:
            ids, first = merge_rounds([w.encode() for w in new], self.tables)
            self.ids = np.concatenate([self.ids, ids])
            self.first = np.concatenate([self.first, self.first[-1] + first[1:]])
        out = []
        for slots in lists:
            begin = self.first[slots]
            sizes = self.first[slots + 1] - begin
            ends = np.cumsum(sizes)
            at = np.arange(ends[-1] if len(ends) else 0) + np.repeat(begin - (ends - sizes), sizes)
            out.append(self.ids[at].astype("<u4").tobytes())
        return out


def encode(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_tokens, token_ids (binary, little-endian unsigned 32-bit) for every row; null texts are empty and have no ids.

    Ids are those of the tokenizer file with special tokens found in the text and none added.  The file is read on the driver
    and its tables (about 2 MB) travel with the plan.
    """
    tables = docs.sparkSession.sparkContext.broadcast(load_tables(tokenizer))
    kind = docs.select(id_col).schema[0].dataType.simpleString()

    def run(batches):
        coder = Encoder(tables.value)
        for whole in batches:
            trim()
            for batch in pieces(whole, "text"):
                coded = coder.encode([t or "" for t in batch.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([len(c) // 4 for c in coded], pa.int64()), pa.array(coded, pa.binary())], ["id", "n_tokens", "token_ids"])

    rows = docs.selectExpr(f"`{id_col}` as id", f"cast(`{text_col}` as string) as text")
    return rows.mapInArrow(run, f"id {kind}, n_tokens bigint, token_ids binary").withColumnRenamed("id", id_col)


def decode(coded: DataFrame, tokenizer: str) -> DataFrame:
    """coded with a further column decoded: the tokens' spellings joined by one space, special tokens kept."""
    names = coded.sparkSession.sparkContext.broadcast(load_tables(tokenizer)["names"])
    fields = coded.drop("decoded")

    def run(batches):
        for batch in batches:
            spell = names.value.__getitem__
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                texts = [" ".join(map(spell, np.frombuffer(b or b"", "<u4").tolist())) for b in part.column("token_ids").to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], [*part.schema.names, "decoded"])

    return fields.mapInArrow(run, StructType([*fields.schema.fields, StructField("decoded", StringType())]))
