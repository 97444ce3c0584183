"""The tables of tokens in the scan for secrets."""

from rankflow.llm import secrets


def test_nothing_is_before_the_first_token():
    scorer = secrets.Scorer(secrets.Field({secrets.AGAIN: (0.0, 1.0, 0.0)}))
    assert scorer.scores(["\n", "a", "\n", "\n", "b"], [])[:, 1].tolist() == [0.0, 0.0, 1.0, 1.0, 0.0]


def test_neighbours_share_rows_and_short_words_their_shape():
    scorer = secrets.Scorer(secrets.Field({"before1 key": (0.0, 2.0, 0.0)}))
    scorer.scores([f"word{'abcdefgh'[k % 8] * (k // 8 % 4 + 1)}" for k in range(32)] + ["Key", "key", "KEY"], [])
    assert scorer.filled == 2 and scorer.owned < len(scorer.rows)
