"""Chat formatting at the level of token ids.

Every text is encoded by itself and reserved ids are spliced in between, so no text can make a marker.
The written form of a marker that occurs inside a text is escaped, which `unescaped` undoes. The loss mask
is the running sum of +1 where an assistant's text begins and -1 where it ends.

Cases: a null text is empty; a null role is an empty one; turns are ordered by (turn, role, text), null first;
a null conversation id is a conversation; an empty table gives none; further columns are ignored. A conversation
of any length is a run of rows of bounded size (part), and only one turn of it is in memory at a time.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, tokens

#: The written markers, in the order of their reserved ids, which follow the vocabulary.
MARKERS = ("<s>", "</s>", "[INST]", "[/INST]", "[SYS]", "[/SYS]", "[ROLE]", "[/ROLE]")
#: Role: markers before and after its text. Any other role is written out between [ROLE] and [/ROLE], and its text ends with </s>.
FRAMES = {"system": ("[SYS]", "[/SYS]"), "user": ("[INST]", "[/INST]"), "assistant": ("<s>", "</s>")}
_CONTROL = r"(<)(\\*)(s>|/s>)|(\[)(\\*)(INST\]|/INST\]|SYS\]|/SYS\]|ROLE\]|/ROLE\])"
_ESCAPE = regex.compile(_CONTROL)


def escaped(text: str) -> str:
    """One more backslash after the first character of every marker, whether or not it has some already."""
    return _ESCAPE.sub(lambda m: (m[1] or m[4]) + "\\" + (m[2] or m[5] or "") + (m[3] or m[6]), text) if "<" in text or "[" in text else text


def unescaped(text: str) -> str:
    return _ESCAPE.sub(lambda m: (m[1] or m[4]) + (m[2] or m[5] or "")[1:] + (m[3] or m[6]), text) if "\\" in text else text


OUTPUT = "conv_id long, part int, input_ids array<int>, loss_mask array<byte>"
_OUTPUT = pa.schema([("conv_id", pa.int64()), ("part", pa.int32()), ("input_ids", pa.list_(pa.int32())), ("loss_mask", pa.list_(pa.int8()))])


def assembled(roles: list[str], texts: list[str], encode: tokens.Encoder, first_marker: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, loss mask) of every turn: the pieces encoded apart, the markers spliced, the mask by a running sum."""
    named = [r not in FRAMES for r in roles]
    ids, at = encode(pa.array([escaped(t) for t in texts] + [escaped(r) if odd else "" for r, odd in zip(roles, named, strict=True)], pa.large_string()))
    marker = {m: np.array([first_marker + k], np.uint32) for k, m in enumerate(MARKERS)}
    n = len(roles)
    for k, role in enumerate(roles):
        text = ids[at[k] : at[k + 1]]
        before, after = FRAMES.get(role, ("[/ROLE]", "</s>"))
        lead = [marker["[ROLE]"], ids[at[n + k] : at[n + k + 1]]] if named[k] else []
        turn = np.concatenate([*lead, marker[before], text, marker[after]])
        steps = np.zeros(len(turn) + 1, np.int8)
        if role == "assistant":
            steps[len(turn) - 1 - len(text)] += 1
            steps[len(turn) - 1] -= 1
        yield turn, np.cumsum(steps[:-1], dtype=np.int8)


def formatted(conversations: DataFrame, tokenizer: str, vocabulary: int, *, part_ids: int = 1 << 16) -> DataFrame:
    """conv_id, part, input_ids, loss_mask; parts of a conversation are consecutive rows of one partition, in order."""
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    dealt = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")

    def assemble(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = tokens.encoder(tokenizer, False)
        conv, part, held, size, started = None, 0, [], 0, False

        def row(ids: np.ndarray, mask: np.ndarray) -> pa.RecordBatch:
            lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x)) for x in (ids.astype(np.int32), mask)]
            return pa.RecordBatch.from_arrays([pa.array([conv], pa.int64()), pa.array([part], pa.int32()), *lists], schema=_OUTPUT)

        out: list[pa.RecordBatch] = []
        waiting = 0
        for batch in batches:
            for some in common.parts(batch, "text", 4 << 20):
                convs = some.column("conv_id").to_pylist()
                for c, (ids, mask) in zip(convs, assembled(some.column("role").to_pylist(), some.column("text").to_pylist(), encode, vocabulary), strict=True):
                    if started and c != conv:
                        out.append(row(*map(np.concatenate, zip(*held, strict=True))))
                        waiting, part, held, size = waiting + size, 0, [], 0
                    conv, started = c, True
                    if size and size + len(ids) > part_ids:
                        out.append(row(*map(np.concatenate, zip(*held, strict=True))))
                        waiting, part, held, size = waiting + size, part + 1, [], 0
                    held.append((ids, mask))
                    size += len(ids)
                    if waiting > 1 << 20:
                        yield pa.Table.from_batches(out).combine_chunks().to_batches()[0]
                        out, waiting = [], 0
        if held:
            out.append(row(*map(np.concatenate, zip(*held, strict=True))))
        if out:
            yield pa.Table.from_batches(out).combine_chunks().to_batches()[0]

    return dealt.mapInArrow(assemble, OUTPUT)


class _Reader:
    """Reads formatted parts back: roles, texts and what lies under the mask."""

    def __init__(self, tokenizer: str, vocabulary: int):
        self.tokenizer, self.first = tokens.encoder(tokenizer, False).tokenizer, vocabulary

    def turns(self, ids: np.ndarray, mask: np.ndarray) -> Iterator[tuple[str, str, str | None, int]]:
        """(role, text, text under the mask, characters of the written form) of each turn of a part."""
        places = np.flatnonzero(ids >= self.first)
        cuts = [*places.tolist(), len(ids)]
        spans = [(MARKERS[int(ids[p]) - self.first], p + 1, cuts[k + 1]) for k, p in enumerate(places.tolist())]
        written = self.tokenizer.decode_batch([ids[a:b].tolist() for _, a, b in spans], skip_special_tokens=False)
        opening = {before: role for role, (before, _) in FRAMES.items()}
        k = 0
        while k < len(spans):
            name, size = opening.get(spans[k][0]), 0
            if name is None:  # [ROLE] name [/ROLE] text </s>
                name, size = unescaped(written[k]), len(MARKERS[6]) + len(written[k])
                k += 1
            _, a, b = spans[k]
            lost = None
            if b > a and mask[a:b].any():
                lost = unescaped(written[k] if mask[a:b].all() else self.tokenizer.decode(ids[a:b][mask[a:b] > 0].tolist(), skip_special_tokens=False))
            size += len(spans[k][0]) + len(written[k]) + len(spans[k + 1][0])
            yield name, unescaped(written[k]), lost, size
            k += 2


DIGESTS = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
_DIGESTS = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])


def digests(parts: DataFrame, tokenizer: str, vocabulary: int) -> DataFrame:
    """Per conversation what its parts hold, read back from ids and mask. parts: as `formatted` leaves them in partitions."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = _Reader(tokenizer, vocabulary)
        conv, started, out = None, False, []
        n = lost_chars = chars = 0
        all_turns = lost_text = None

        def row() -> dict:
            return {"conv_id": conv, "n_turns": n, "turns_sha256": all_turns.hexdigest(), "loss_chars": lost_chars, "loss_sha256": lost_text.hexdigest(), "formatted_chars": chars}

        for batch in batches:
            ids_at, ids = (x := batch.column("input_ids")).offsets.to_numpy(), x.values.to_numpy()
            mask = batch.column("loss_mask").values.to_numpy()
            for k, c in enumerate(batch.column("conv_id").to_pylist()):
                if not started or c != conv:
                    if started:
                        out.append(row())
                    conv, started, n, lost_chars, chars = c, True, 0, 0, 0
                    all_turns, lost_text = hashlib.sha256(), hashlib.sha256()
                for role, text, lost, size in reader.turns(ids[ids_at[k] : ids_at[k + 1]], mask[ids_at[k] : ids_at[k + 1]]):
                    n, chars = n + 1, chars + size
                    all_turns.update(f"{role}\n{text}\n".encode())
                    if lost:
                        lost_chars += len(lost)
                        lost_text.update(lost.encode())
            if len(out) >= 10_000:
                yield pa.RecordBatch.from_pylist(out, schema=_DIGESTS)
                out = []
        if started:
            out.append(row())
        if out:
            yield pa.RecordBatch.from_pylist(out, schema=_DIGESTS)

    return parts.mapInArrow(read, DIGESTS)
