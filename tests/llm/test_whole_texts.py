import numpy as np

from tagroute.llm import toxicity_ws


def test_shouting_is_counted_over_whole_texts():
    none = toxicity_ws.Lexicon(np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), 24)
    texts = [("quiet " * 400 + "LOUD " * 2000).encode(), ("LOUD " * 400 + "quiet " * 2000).encode(), ("\u00c4\u00d6" * 9 + "AAAAA").encode(), b""]
    votes, x = toxicity_ws._numbers(none, texts)
    brute = [sum(map(str.isupper, t.decode())) / max(1, len(t)) > 0.5 for t in texts]
    assert (votes[:, 24 + 4] == -1).tolist() == brute == [True, False, True, False]
    assert toxicity_ws._numbers(none, texts, voting=False)[0] is None and (toxicity_ws._numbers(none, texts, voting=False)[1] == x).all()
