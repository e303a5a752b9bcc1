"""Models of both kinds, written out by hand: normalisers, spaces, prefixes and byte fallback, against the library."""

import itertools
import random
import struct

import pyarrow as pa
import pytest

from semjoin.llm import sentencepiece_codec as codec

TEXTS = ["", " ", "the cat", "  the   cat ", "thecat\tsat", "ﬁne ① Ａbc", "a\nb", "é😀", "cat▁the", "the the  the", "x", "unknown œ words", "ca t", " lead", "trail "]


def _varint(n):
    out = b""
    while n > 127:
        out, n = out + bytes([n & 127 | 128]), n >> 7
    return out + bytes([n])


def _field(number, value):
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


def _model(kind, bytes_too, charsmap, prefix, extra, more=()):
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3)]
    if bytes_too:
        pieces += [(f"<0x{i:02X}>", 0.0, 6) for i in range(256)]
    words = ["▁the", "▁cat", "th", "the", "cat", "ca", "he", "▁t", "▁th", "at", "▁c", "▁ca", "sat", "sa", "fi", "fine", "ine", "ne", *more]
    letters = ["▁", *"abcdefhinorstuwk1A"]
    pieces += [(w, -1.0 - 0.37 * i, 1) for i, w in enumerate(words)] + [(c, -12.0 - 0.11 * i, 1) for i, c in enumerate(letters)]
    body = b"".join(_field(1, _field(1, p.encode()) + _field(2, s) + _field(3, k)) for p, s, k in pieces)
    trainer = _field(3, kind) + _field(35, int(bytes_too)) + _field(40, 0) + _field(41, 1) + _field(42, 2)
    normal = _field(1, b"own") + _field(2, charsmap) + _field(3, int(prefix)) + _field(4, int(extra)) + _field(5, 1)
    return body + _field(2, trainer) + _field(3, normal)


def _charsmap():
    import sentencepiece

    made = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc").serialized_model_proto()
    return dict(codec.fields(dict(codec.fields(made))[3]))[2]


@pytest.mark.parametrize("kind, bytes_too, mapped, prefix, extra", [x for x in itertools.product((1, 2), (True, False), (False, True), (True, False), (True, False))])
def test_any_model(tmp_path, kind, bytes_too, mapped, prefix, extra):
    import sentencepiece

    path = tmp_path / "m.model"
    path.write_bytes(_model(kind, bytes_too, _charsmap() if mapped else b"", prefix, extra))
    reference = sentencepiece.SentencePieceProcessor(model_file=str(path))
    c = codec.Codec(str(path))
    assert (c.model.kind, c.model.byte_fallback, bool(c.model.charsmap), c.model.dummy_prefix, c.model.remove_extra) == (kind, bytes_too, mapped, prefix, extra)
    q = random.Random(kind)
    parts = ["the", "cat", " ", "  ", "t", "h", "ca", "ﬁ", "①", "\t", "é", "s", "▁", "z"]
    texts = TEXTS + ["".join(q.choice(parts) for _ in range(9)) for _ in range(400)]
    ids, at, _, differ = c.encode(pa.array(texts, pa.large_string()))
    got = [ids[a:b].tolist() for a, b in zip(at, at[1:])]
    want = reference.encode(texts)
    assert [(t, g, w) for t, g, w in zip(texts, got, want) if g != w] == []
    assert not differ.any()
    known = [t for t, w in zip(texts, want) if 0 not in w and "▁" not in t]
    assert [c.decode(reference.encode(t)) for t in known] == [reference.decode(reference.encode(t)) for t in known]


def test_ties_are_counted(tmp_path):
    """Three markers as 2 + 1 or 1 + 2 score the same, and the two libraries may choose differently: that is told."""
    import sentencepiece

    path = tmp_path / "m.model"
    path.write_bytes(_model(1, True, b"", True, False, ("▁▁",)))
    c, reference = codec.Codec(str(path)), sentencepiece.SentencePieceProcessor(model_file=str(path))
    texts = ["the cat", "a   z", "h   é", "   ", "é  ▁é"]
    ids, at, _, differ = c.encode(pa.array(texts, pa.large_string()))
    assert [ids[a:b].tolist() != reference.encode(t) for t, a, b in zip(texts, at, at[1:])] == (differ > 0).tolist()


def test_differences_are_told(spark, tmp_path, monkeypatch):
    """A backend that goes wrong is counted, and raises where that is asked for; its ids are not replaced."""
    path = tmp_path / "m.model"
    path.write_bytes(_model(1, True, b"", True, False))
    c = codec.Codec(str(path))
    _, _, _, none = c.encode(pa.array(["the cat"], pa.large_string()))
    c.forget()
    texts = ["the cat", "thecat sat", "fine the"]

    class Off:
        """Gives one id too few."""

        def encode_batch_fast(self, chunks, **options):
            return [type("E", (), {"ids": e.ids[1:]}) for e in real.encode_batch_fast(chunks, **options)]

    real = c.inner
    monkeypatch.setattr(c, "inner", Off())
    wrong, _, _, differ = c.encode(pa.array(texts, pa.large_string()))
    assert none.sum() == 0 and (differ > 0).all() and len(wrong) < len([x for t in texts for x in c.reference.encode(t)])
    df = spark.createDataFrame([(1, "the cat"), (2, None)], "doc_id bigint, text string")
    assert codec.encode(df, path=str(path), strict=True).where("n_differ > 0").count() == 0
