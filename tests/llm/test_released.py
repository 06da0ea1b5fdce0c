"""Workers that are kept for other stages hand back what a task freed."""

from patternldp.llm import arrowmap


def test_memory_is_released_at_the_end_of_a_task_and_after_an_error(monkeypatch):
    calls = []
    monkeypatch.setattr(arrowmap, "release_memory", lambda: calls.append(1))
    assert list(arrowmap.released(lambda batches: (b + 1 for b in batches))(iter([1, 2]))) == [2, 3] and calls == [1]

    def bad(batches):
        yield next(batches)
        raise ValueError

    try:
        list(arrowmap.released(bad)(iter([1])))
    except ValueError:
        pass
    assert calls == [1, 1]
