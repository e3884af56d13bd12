"""A text is split and hashed once for its votes and its features."""

import numpy as np

from dictparse.llm import toxicity as T


def test_votes_and_features_share_hashes():
    texts = ["", "idiot IDIOT!! moron", "abandon abandoned abandoning", "Scum of the earth, scummy scum!!!"]
    hasher = T.Hasher()
    lexicon = np.unique(np.concatenate([hasher.features(t) for t in texts]))
    votes, alone = T.Votes(lexicon), T.Votes(lexicon)
    for t in texts:
        parts = hasher.parts(t)
        assert votes.pattern(t, parts) == alone.pattern(t)
        assert sorted(hasher.features(t, parts).tolist()) == sorted(hasher.features(t).tolist())
    assert not votes.hasher.known and alone.hasher.known


def test_features_of_beginnings():
    own = T.Hasher().features("abcdefg abcdefh abcdz")
    kinds = np.bincount((own & np.uint64(3)).astype(int), minlength=4).tolist()
    # three words; beginnings abcd (of three words) and abcdef (of two)
    assert kinds == [3, 2, 2, 1]


def test_a_batch_is_scored_as_its_texts_are():
    texts = ["", "idiot IDIOT!! moron", "abandon abandoned abandoning ABANDON", "Scum of the earth, scummy scum!!!", "scummy scumbag scumming earthly", "été étéindre"] * 2
    hasher = T.Hasher()
    lexicon = np.unique(np.concatenate([hasher.features(t) for t in texts]))[::3]
    votes = T.Votes(lexicon)
    patterns = np.array([votes.pattern(t, hasher.parts(t)) for t in texts], np.int64)
    features = [hasher.features(t) for t in texts]
    linear = T.Linear(features, patterns, patterns > 3, rounds=5)
    for bound in (150_000, 2):  # words are forgotten beyond the bound
        alone, scorer = T.Votes(lexicon), T.Scorer(T.Votes(lexicon), linear)
        alone.hasher.bound = scorer.votes.hasher.bound = bound
        assert [alone.pattern(t) for t in texts] == patterns.tolist()
        # only words that some lexicon may know are hashed with their beginnings
        assert len(alone.hasher.known) < len({w for t in texts for w in T._words(t)})
        got = np.concatenate([scorer.scores(texts[k : k + 5]) for k in range(0, len(texts), 5)])
        assert np.allclose(got, linear.score(patterns, features), atol=1e-6)
    assert len(scorer.scores([])) == 0
