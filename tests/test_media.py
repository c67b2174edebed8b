"""Media references are read late and held only while a request is in flight; ways of keeping rows."""

import json
import threading
import time

import pandas as pd
import pytest

from lmrel.operators.executor import _worker, with_answers
from lmrel.session import Runtime, lm_map, materialise
from lmrel.sources import media
from lmrel.sources.providers import HttpProvider, Request


def loud():
    """A model that says whether a sample is louder than 100; it needs the bytes."""

    class Loud:
        name = "loud"

        def complete(self, r):
            return str(max(b for _, own in r.media for b in own) > 100).lower(), 1, 1

    return Loud()


@pytest.fixture(scope="module")
def sounds(tmp_path_factory):
    path = tmp_path_factory.mktemp("sounds") / "all.bin"
    path.write_bytes(bytes(range(200)))
    return str(path)


def test_parts_of_a_file_are_judged(spark, sounds):
    rows = [(i, sounds if i % 2 else f"file://{sounds}", 10 * i, 10) for i in range(20)] * 2 + [(99, None, 0, 1)]
    df = spark.createDataFrame(rows, "id long, place string, at long, n long").withColumn("sound", media.media("place", "audio", "at", "n"))
    rt = Runtime(provider=loud())
    got = {r.id: r.loud for r in with_answers(df, lm_map("Is it loud?", "sound", return_type="bool", modality="audio"), "loud", rt).collect()}
    assert got == {i: 10 * i + 9 > 100 for i in range(20)} | {99: None}
    assert rt.calls == 20


def test_a_missing_file_is_an_error_of_its_row(spark, sounds):
    df = spark.createDataFrame([(1, sounds), (2, sounds + ".none")], "id long, place string").withColumn("sound", media.media("place", "audio"))
    call = lm_map("Is it loud?", "sound", return_type="bool", modality="audio")
    got = with_answers(df, call, "loud", Runtime(provider=loud(), fail_fast=False)).orderBy("id").collect()
    assert [r.loud for r in got] == [True, None]


@pytest.mark.parametrize("concurrency", [1, 4])
def test_media_in_memory_are_bounded(monkeypatch, concurrency):
    live, most, lock = set(), [0], threading.Lock()

    class Slow:
        name = "slow"

        def complete(self, r):
            with lock:
                live.add(id(r))
                most[0] = max(most[0], 2 * len(live))
            time.sleep(0.002)
            with lock:
                live.discard(id(r))
            return "true" if len(r.media) == 2 else "false", 1, 1

    read = []
    monkeypatch.setattr(media, "read", lambda reference: read.append(reference["media_uri"]) or b"x" * 10)
    ref = lambda i: {"media_uri": f"/m/{i}", "media_kind": "image", "media_offset": None, "media_length": None}
    frames = [pd.DataFrame({"k": [b"%d" % i for i in range(a, a + 50)], "inputs": [json.dumps({"x": ref(i), "y": ref(i + 1)}) for i in range(a, a + 50)]}) for a in (0, 50, 100)]
    call = lm_map("Is it the same animal?", "x", "y", return_type="bool", modality="image")
    out = pd.concat(_worker(call, Runtime(provider=Slow(), max_concurrency=concurrency))(iter(frames)))
    assert len(out) == 150 and set(out["value"]) == {"true"} and len(read) == 300
    assert 2 <= most[0] <= 2 * concurrency


def test_media_go_along_to_an_endpoint(monkeypatch):
    seen = {}

    class Reply:
        __enter__, __exit__ = lambda self: self, lambda self, *a: None
        read = lambda self, *a: json.dumps({"choices": [{"message": {"content": "true"}}]}).encode()

    monkeypatch.setattr("urllib.request.urlopen", lambda request, timeout: seen.update(json.loads(request.data)) or Reply())
    call = lm_map("Is it loud?", "sound", return_type="bool")
    assert HttpProvider("http://there", "m").complete(Request("q", "{}", "prompt", call.constraint, "audio", media=(("audio", b"ab"),)))[0] == "true"
    assert [p["type"] for p in seen["messages"][0]["content"]] == ["audio_url", "text"]


def test_ways_of_keeping_rows(spark):
    df = spark.range(5)
    assert materialise(df, "none") is df
    assert materialise(df, "auto").count() == materialise(df, "cache").count() == 5
    df.unpersist()
    for mode in ("checkpoint", "other"):
        if mode == "other" or spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
            with pytest.raises(ValueError):
                materialise(df, mode)
    with pytest.raises(ValueError):
        with_answers(spark.createDataFrame([("red",)], "name string"), lm_map("Is it red?", "name", return_type="bool"), "r", Runtime(answers_in="none"))
