"""What a worker remembers of pre-tokens."""

from nudgegraph.llm.bpe import Coder, PerfectHash


def test_many_pre_tokens_are_not_learned_twice():
    tokens = [bytes([i]) for i in range(256)]
    code = Coder(tokens, list(range(256)), PerfectHash(tokens), r"\S+")
    code.learn([str(i) for i in range(200_000)])
    code.learn(["another"])
    assert len(code.known) == 200_001
