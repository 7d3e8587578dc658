"""State maps of chunks, their composition, and the bound on compiled states."""

import random

import public_tokenizers
import pytest
import sentencepiece

from rowblock.llm import piece_machine
from rowblock.llm.piece_machine import ChunkMap, Machine, MARK, StreamingEncoder, Vocabulary, machine, scan

PIECES = public_tokenizers.path("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def sp():
    return sentencepiece.SentencePieceProcessor(model_file=PIECES)


def hard(seed, n):
    rng = random.Random(seed)
    return "".join(rng.choice("aehllothequickbrown 漢é0\n ") for _ in range(n)), "".join(rng.choice("aehllothequickbrownst") for _ in range(n))


@pytest.mark.parametrize("chunk", [1, 2, 5, 17, 100, 8192])
def test_counts_do_not_depend_on_the_chunks(sp, chunk):
    m = machine(PIECES)
    for k in range(20):
        for t in (*hard(k, 300), " " * k, "a" + "  b" * k, "thequick" * 60):
            assert m.count(t, chunk) == len(sp.encode(t)), (repr(t), chunk)


def test_a_map_gives_what_a_run_gives_from_any_state():
    m = machine(PIECES)
    for k in range(30):
        mixed, solid = hard(k, 120)
        for chunk in (mixed, solid, solid[:3], " " + mixed, solid + " "):
            own = ChunkMap(m, chunk)
            for before in (MARK, MARK + solid[:k], "é", "thequi"):
                entry, _ = m.run(m.start, before)
                state, n = m.run(entry, chunk.replace(" ", MARK))
                assert own(entry) == (state, n)


def test_a_spaceless_chunk_is_a_map_and_joins_after_a_few_characters():
    m, steps = machine(PIECES), 0
    text = "thequickbrownfoxjumps" * 400
    own = ChunkMap(m, text)
    own(m.run(m.start, MARK + "ov")[0])
    entry, _ = m.run(m.start, MARK + "thes")
    state = entry
    for steps, (char, (met, _)) in enumerate(zip(text, own.path), 1):  # noqa: B007
        state = state[char][0]
        if state is met:
            break
    assert steps <= 4 * m.v.longest < len(text)


def test_composition_is_associative():
    m = machine(PIECES)
    text = hard(3, 400)[0] + "x" * 50 + hard(4, 200)[1]
    parts = [text[i : i + 40] for i in range(0, len(text), 40)]
    left = ChunkMap(m, parts[0])
    for p in parts[1:]:
        left = scan([left, ChunkMap(m, p)])
    assert left(m.start) == scan([ChunkMap(m, p) for p in parts])(m.start)


def test_states_stay_bounded_and_results_right(sp, monkeypatch):
    monkeypatch.setattr(piece_machine, "MOST_STATES", 2000)
    m = Machine(Vocabulary.load(PIECES))
    rng = random.Random(8)
    text = "".join(rng.choice("aehlotqickbrwnzxdgéü漢") for _ in range(40_000))
    ids = sp.encode(text)
    assert m.count(text) == len(ids) and len(m.states) <= 2000 + 2 * piece_machine.CHUNK + piece_machine.LOOK
    assert m.encode(text) == ids and len(m.states) <= 2000 + piece_machine.LOOK
    encoder, out = StreamingEncoder(m), []
    for at in range(0, len(text), 777):
        out += encoder.feed((MARK if at == 0 else "") + text[at : at + 777])
        assert len(m.states) <= 2000 + piece_machine.LOOK
    assert [*out, *encoder.finish()] == ids
