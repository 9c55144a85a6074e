"""Chat formatting at the level of tokens.

A turn is OPEN role BODY text CLOSE: role and text are encoded separately and the three reserved ids, which lie above
the vocabulary, are spliced between them, so no content can produce them. Printed, the reserved ids are control
strings on lines of their own; control strings inside contents (these and those of other templates) get one more
backslash in front, which is taken off when reading back. The loss mask is the prefix sum of +1 after BODY and -1 at
CLOSE of assistant turns.

Turns are ordered by turn, then role and text. Null text and null role count as empty; a null conversation id is a conversation
of its own. Repeated rows are turns of their own. An empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxprune.llm.bpe import codec

#: Printed control strings of this template, then those of common other ones.
OPEN, BODY, CLOSE = "<|turn|>", "<|text|>", "<|end|>"
FOREIGN = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|im_start|>", "<|im_end|>", "<|endoftext|>", "<|system|>", "<|user|>", "<|assistant|>")
CONTROLS = (OPEN, BODY, CLOSE, *FOREIGN)
LOSS_ROLE = "assistant"

_ANY = "|".join(re.escape(c) for c in CONTROLS)
_ADD = re.compile(rf"(\\*)({_ANY})")
_TAKE = re.compile(rf"\\(\\*)({_ANY})")


def escape(text: str) -> str:
    return _ADD.sub(r"\\\1\2", text) if "<" in text or "[" in text else text  # every control string holds one of them


def unescape(text: str) -> str:
    return _TAKE.sub(r"\1\2", text) if "\\" in text else text


def printed(role: str, text: str) -> str:
    return f"{OPEN}{escape(role)}\n{BODY}{escape(text)}\n{CLOSE}"


class Assembler:
    def __init__(self, path: str, pattern: str):
        self.codec = codec(path, pattern)
        self.reserved = len(self.codec.bpe.pieces) + 1 + np.arange(3)  # one id is kept free for the end of text

    def turns(self, roles: list[str], texts: list[str]) -> tuple[list[np.ndarray], list[np.ndarray]]:
        """ids and loss mask of each turn."""
        heads, bodies = ([np.frombuffer(b"".join([x[0] for x in c]), "<u4").astype(np.int32) for c in self.codec.encode([escape(s) for s in part])] for part in (roles, texts))
        o, b, c = (np.array([x], np.int32) for x in self.reserved)
        ids, masks = [], []
        for role, head, body in zip(roles, heads, bodies, strict=True):
            ids.append(np.concatenate([o, head, b, body, c]))
            edges = np.zeros(len(ids[-1]), np.int8)
            if role == LOSS_ROLE and len(body):
                edges[len(head) + 2] = 1
                edges[-1] = -1
            masks.append(np.cumsum(edges, dtype=np.int8))
        return ids, masks

    def read_back(self, ids: np.ndarray, mask: np.ndarray) -> tuple[str, str, str]:
        """Role, text, and text under the mask of one turn's ids."""
        bodies = np.flatnonzero(ids == self.reserved[1])
        if ids[0] != self.reserved[0] or ids[-1] != self.reserved[2] or len(bodies) != 1:
            raise ValueError("not one formatted turn")
        at = int(bodies[0])
        text = lambda part: unescape(self.codec.bpe.decode(part.tolist()).decode())
        under, own = ids[mask > 0], text(ids[at + 1 : -1])
        # what the mask covers is decoded once if it is the body itself
        return text(ids[1:at]), own, own if np.array_equal(under, ids[at + 1 : -1]) else text(under)


def format_turns(turns: DataFrame, path: str, pattern: str, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """conv_id, turn, ids, loss_mask, formatted (the printed turn); a conversation is its turns in order."""
    kinds = [turns.schema[c].dataType.simpleString() for c in (conv_col, turn_col)]

    def job(batches):
        a = Assembler(path, pattern)
        for b in batches:
            roles, texts = ([x or "" for x in b.column(i).to_pylist()] for i in (2, 3))
            ids, masks = a.turns(roles, texts)
            shown = [printed(r, t) for r, t in zip(roles, texts, strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ids, pa.list_(pa.int32())), pa.array(masks, pa.list_(pa.int8())), pa.array(shown, pa.string())], names=["conv_id", "turn", "ids", "loss_mask", "formatted"])

    picked = turns.select(F.col(conv_col).alias("conv_id"), F.col(turn_col).alias("turn"), F.col(role_col).cast("string").alias("role"), F.col(text_col).alias("text"))
    return picked.mapInArrow(job, f"conv_id {kinds[0]}, turn {kinds[1]}, ids array<int>, loss_mask array<tinyint>, formatted string")


def read_turns(formatted: DataFrame, path: str, pattern: str) -> DataFrame:
    """conv_id, turn, role, text, loss_text and formatted_chars, read back from ids and masks."""
    kinds = [formatted.schema[c].dataType.simpleString() for c in ("conv_id", "turn")]

    def job(batches):
        a = Assembler(path, pattern)
        for b in batches:
            ids, masks = b.column("ids"), b.column("loss_mask")
            got = [a.read_back(i.values.to_numpy(), m.values.to_numpy()) for i, m in zip(ids, masks, strict=True)]
            cols = [pa.array([g[k] for g in got], pa.string()) for k in range(3)]
            yield pa.RecordBatch.from_arrays([b.column("conv_id"), b.column("turn"), *cols, pa.array([len(s) for s in b.column("formatted").to_pylist()], pa.int64())], names=["conv_id", "turn", "role", "text", "loss_text", "formatted_chars"])

    return formatted.mapInArrow(job, f"conv_id {kinds[0]}, turn {kinds[1]}, role string, text string, loss_text string, formatted_chars long")


def conversation_digests(read: DataFrame) -> DataFrame:
    """One row a conversation. Sorted turns stream through running hashes, so a conversation is never held
    in memory, however long it is."""
    kind = read.schema["conv_id"].dataType.simpleString()

    def job(batches):
        key, n, chars, loss, turns_hash, loss_hash = (), 0, 0, 0, None, None
        for b in batches:
            out = []
            for conv, role, text, under, size in zip(*[b.column(c).to_pylist() for c in ("conv_id", "role", "text", "loss_text", "formatted_chars")], strict=True):
                if key != (conv,):
                    if key:
                        out.append((key[0], n, turns_hash.hexdigest(), loss, loss_hash.hexdigest(), chars))
                    key, n, chars, loss, turns_hash, loss_hash = (conv,), 0, 0, 0, hashlib.sha256(), hashlib.sha256()
                n, chars, loss = n + 1, chars + size, loss + len(under)
                turns_hash.update(f"{role}\n{text}\n".encode())
                loss_hash.update(under.encode())
            yield _digest_batch(out, b.schema.field("conv_id").type)
        if key:
            yield _digest_batch([(key[0], n, turns_hash.hexdigest(), loss, loss_hash.hexdigest(), chars)], None)

    ordered = read.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return ordered.mapInArrow(job, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def _digest_batch(rows: list[tuple], kind) -> pa.RecordBatch:
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
    types = [kind or pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=names)
