"""A worker's tasks share what they have learnt."""

from divknn.llm import tokens
from divknn.llm.tokens import vocabulary_path

from .helpers import AWKWARD
from .test_tokens import TRICKY, ids_of


def test_second_task_learns_nothing(monkeypatch):
    rows = [r for r in AWKWARD + TRICKY if r[1]]
    texts = [t.encode() for _, t in rows]
    learnt = []
    learn = tokens.ChunkEncoder._learn
    monkeypatch.setattr(tokens.ChunkEncoder, "_learn", lambda self, fresh: (learnt.append(len(fresh)), learn(self, fresh)))
    monkeypatch.setattr(tokens, "_ENCODERS", {})
    want = [x for _, ids in ids_of(rows, 2) for x in ids]
    for _ in range(2):  # two tasks of one worker process
        ids, _ = tokens.encoder(vocabulary_path()).encode(texts, 2)
        assert ids.tolist() == want
    assert len(learnt) == 1


def test_kept_encoder_starts_afresh():
    """The caches stay bounded however many texts a worker sees."""
    small = tokens.ChunkEncoder(vocabulary_path(), most=20)
    for i in range(30):
        rows = [(0, " ".join(f"wörd{i}x{j} plain{i * j}" for j in range(15)))]
        ids, _ = small.encode([rows[0][1].encode()], 2)
        assert ids.tolist() == ids_of(rows, 2)[0][1]
        assert len(small.chunks.place) <= 20 + 30
