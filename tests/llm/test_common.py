"""What the operators share."""

from ownerdp.llm import common
from ownerdp.llm.common import per_worker


def test_a_worker_makes_each_kind_once_for_each_key():
    made = []

    def make(value):
        return lambda: made.append(value) or value

    assert per_worker("test-kind", "", make("first")) == "first"  # the empty key is a key like any other
    assert per_worker("test-kind", "", make("again")) == "first"
    assert per_worker("test-kind", "other", make("second")) == "second"
    assert per_worker("test-other-kind", "", make("third")) == "third"
    assert made == ["first", "second", "third"]


def test_keeping_freed_memory_fails_nowhere(monkeypatch):
    common.keep_freed_memory()
    monkeypatch.setattr(common.ctypes, "CDLL", lambda _: object())
    common.keep_freed_memory()
