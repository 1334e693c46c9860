"""SentencePiece coding against the library and against the agenda by its definition."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest
import sentencepiece

from linkfactor.llm import pieces
from linkfactor.llm.cluster import table
from linkfactor.llm.queries_pieces import model_path, op2_sentencepiece

MID = "/root/testdata/sf0.01"
ODD = ["", " ", "  lead", "a  b   c ", "x\n\ny\tz", "漢字🎉 é́", "a▁b ▁", "\x00\x7f", "w" * 900, "ab" * 40 + " " * 70 + "z"]


def coded(coder, texts, salts=None):
    ids, sizes = coder.encode(pa.array(texts, type=pa.string()), np.arange(len(texts)) if salts is None else np.array(salts, dtype=np.int64))
    return [x.tolist() for x in np.split(ids, np.cumsum(sizes)[:-1])] if texts else []


def test_without_dropout_it_is_the_library(spark):
    library = sentencepiece.SentencePieceProcessor(model_file=model_path())
    coder = pieces.PieceCoder(model_path(), 1, 0.0)
    texts = [r.text for r in table(spark, MID, "documents").collect()] + [t for t in ODD if "▁" not in t]
    for t, ids in zip(texts, coded(coder, texts), strict=True):
        assert ids == library.encode(t), t
    assert [coder.decode(np.array(x, dtype=int)) for x in coded(coder, ODD)] == ODD


MASK = (1 << 64) - 1


def plain_mix(x):
    x = (x + 0x9E3779B97F4A7C15) & MASK
    x = (x ^ x >> 30) * 0xBF58476D1CE4E5B9 & MASK
    x = (x ^ x >> 27) * 0x94D049BB133111EB & MASK
    return x ^ x >> 31


class Agenda:
    """Merge-dropout by the definition: strings of pieces, all candidates looked at anew for each merge."""

    def __init__(self, seed, rate):
        model = sentencepiece.SentencePieceProcessor(model_file=model_path())
        n = model.get_piece_size()
        special = [model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i) for i in range(n)]
        self.ids = {model.id_to_piece(i): i for i in range(n) if not special[i]}
        self.score = {p: model.get_score(i) for p, i in self.ids.items()}
        self.byte = {int(model.id_to_piece(i)[3:5], 16): i for i in range(n) if model.is_byte(i)}
        extra = [c for p in self.ids for c in p if c not in self.ids]
        self.symbol = self.ids | {c: n + k for k, c in enumerate(dict.fromkeys(extra))}
        self.seed, self.limit = plain_mix(seed), int(rate * 2**64)

    def part(self, part, salt):
        pieces = [c if c != " " else "▁" for c in part]
        blocked = [c == "▁" for c in part]  # a literal mark is no piece
        places = list(range(len(pieces)))
        while True:
            best = None
            for i in range(len(pieces) - 1):
                both = pieces[i] + pieces[i + 1]
                if blocked[i] or blocked[i + 1] or both not in self.ids:
                    continue
                left, right = self.symbol[pieces[i]], self.symbol[pieces[i + 1]]
                code = plain_mix(left << 32 | right) ^ places[i] * 0xD6E8FEB86659FD93 & MASK
                if plain_mix(code ^ salt) < self.limit:
                    continue
                order = (-self.score[both], self.ids[both], i)
                if best is None or order < best[0]:
                    best = (order, i, both)
            if best is None:
                break
            _, i, both = best
            pieces[i : i + 2], places[i + 1 : i + 2], blocked[i + 1 : i + 2] = [both], [], []
        out = []
        for p, bad in zip(pieces, blocked, strict=True):
            out += [self.byte[b] for b in p.encode()] if bad or p not in self.ids else [self.ids[p]]
        return out

    def text(self, text, salt):
        out, at, whole = [], 0, " " + text
        own = plain_mix(salt & MASK ^ self.seed)
        for part in re.findall(" *[^ ]+| +", whole) if text else []:
            out += self.part(part, plain_mix(own ^ at * 0x9E3779B97F4A7C15 & MASK))
            at += len(part.encode())
        return out


@pytest.mark.parametrize("rate", [0.1, 0.4])
def test_dropout_is_the_agendas_by_definition(rate, monkeypatch):
    monkeypatch.setattr(pieces, "CACHE_PARTS", 300)
    coder, agenda, rng = pieces.PieceCoder(model_path(), 9, rate), Agenda(9, rate), random.Random(8)
    words = ["the", "international", "of", "information", "Straße", "漢字", "a▁b", "x\ny.", "é́", "interesting,", "w" * 70, "ab" * 40]
    texts = [" ".join(rng.choices(words, k=rng.randrange(1, 12))) for _ in range(60)]
    texts += ["".join(rng.choice("aehnorst▁é漢 ,.") for _ in range(rng.randrange(0, 40))) for _ in range(120)] + ODD
    salts = [rng.randrange(-(1 << 63), 1 << 63) for _ in texts]
    for _ in range(2):  # from an empty and from a filled table
        got = coded(coder, texts, salts)
        for t, s, ids in zip(texts, salts, got, strict=True):
            assert ids == agenda.text(t, s), t


def test_every_occurrence_draws_for_itself():
    coder = pieces.PieceCoder(model_path(), 1, 0.1)
    one, two = coded(coder, ["international " * 400 + "end"] * 2, [5, 6])
    assert one != two and one == coded(coder, ["international " * 400 + "end"], [5])[0]
    cuts, word = set(), []
    for i in one:  # a word begins with a piece that begins with a space
        if coder.bytes_of[i].startswith(b" "):
            cuts.add(tuple(word))
            word = []
        word.append(i)
    assert len(cuts) > 12
    share = 1 - sum(x == y for x, y in zip(one, pieces.PieceCoder(model_path(), 1, 0.0).encode(pa.array(["international"]), np.array([5]))[0].tolist() * 400, strict=False)) / len(one)
    assert share > 0.1


def test_dropout_decodes():
    texts = ["the international information about something interesting " * 5, *ODD]
    library = sentencepiece.SentencePieceProcessor(model_file=model_path())
    runs = [coded(pieces.PieceCoder(model_path(), s, 0.1), texts) for s in (1, 2)]
    assert runs[0][0] != runs[1][0] and runs[0] == coded(pieces.PieceCoder(model_path(), 1, 0.1), texts)
    coder = pieces.PieceCoder(model_path(), 1, 0.1)
    for r in runs:
        assert [coder.decode(np.array(x, dtype=int)) for x in r] == texts
        assert library.decode(r[0]) == texts[0]
        flat, sizes = np.array([i for x in r for i in x]), np.array([len(x) for x in r])
        assert coder.is_text(flat, sizes, pa.array(texts)).all()
        other = ["X" + t[1:] for t in texts]
        assert coder.is_text(flat, sizes, pa.array(other)).tolist() == [a == b for a, b in zip(texts, other, strict=True)]
    cut = coded(coder, ["漢"])[0]
    assert coder.decode(np.array([*cut[:-1], 10**6, -4])).endswith("\ufffd")


def test_op2(spark):
    docs = {r.doc_id: r.text for r in table(spark, MID, "documents").collect()}
    library = sentencepiece.SentencePieceProcessor(model_file=model_path())
    rows = op2_sentencepiece(spark, MID).collect()
    assert len(rows) == len(docs) and all(r.lossless and r.n_tokens == len(r.ids) for r in rows)
    for r in rows[:100]:
        assert library.decode(r.ids) == docs[r.doc_id].replace("▁", " ")
    assert sum(r.n_tokens for r in rows) > 1.02 * sum(map(len, library.encode(list(docs.values()))))


def test_pieces_of_odd_rows(spark):
    rows = [(i, t, 1) for i, t in enumerate(ODD)] + [(None, "null key", 1), (3, None, 1), (3, None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids int")
    coded = pieces.encode_pieces(docs, model_path())
    got = coded.collect()
    assert len(got) == len(rows) and all(r.lossless for r in got)
    back = pieces.decode_pieces(coded, model_path()).collect()
    assert sorted(r.text for r in back) == sorted(t or "" for _, t, _ in rows)
    assert pieces.encode_pieces(docs.limit(0), model_path()).count() == 0
