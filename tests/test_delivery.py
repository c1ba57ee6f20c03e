"""Playlists, the service, the sandbox, streams and the oracle sheet."""

import pytest

from reelspark.dialog import show_me as dialog
from reelspark.lift.shim import ClipMeta
from reelspark.model.schemas import segment_frames
from reelspark.sources import codec, derive, gopindex
from reelspark.vod import segments, service
from reelspark.workloads.clips import task_sources


def test_segment_lengths():
    assert [segment_frames(*f) for f in ((30, 1), (30000, 1001), (24, 1), (1, 4), (25, 1))] == [60, 60, 48, 1, 50]


@pytest.mark.parametrize(("pushed", "open_", "closed"), [(0, 0, 0), (59, 0, 1), (60, 1, 1), (119, 1, 2), (120, 2, 2)])
def test_first_segment_after_sixty_frames(spark, pushed, open_, closed):
    log = spark.createDataFrame([("s", k, 1) for k in range(pushed)], "spec_id string, ord bigint, frames bigint")
    assert segments.event_rows(log, 60, close_last=False).count() == open_
    assert segments.event_rows(log, 60).count() == closed


def test_prefix_of_pushes_out_of_order_and_twice(spark):
    gens = [0, 1, 2, 3, 3, 5, 4, 7]
    row = segments.prefix(spark.createDataFrame([("s", g) for g in gens], "spec_id string, gen bigint"), 2).first()
    assert (row["prefix"], row["listed"]) == (6, 3)


@pytest.fixture(scope="module")
def service_parts(spark, sf_dir, tmp_path_factory):
    store = service.Store(spark, "file://" + str(tmp_path_factory.mktemp("store")))
    manager = service.Manager(store, task_sources(spark, sf_dir))
    gops = gopindex.encode(derive.main_frames(spark, sf_dir)).cache()
    return manager, service.Delivery(manager, gops, keep=2)


def ref(i):
    return [{"op": "ref", "kids": [], "ints": [i], "text": "main"}]


def test_service_life_cycle(service_parts):
    manager, delivery = service_parts
    assert manager.create("a", 16, 16) == "/a/playlist.m3u8"
    with pytest.raises(KeyError):
        manager.create("a", 16, 16)
    assert "#EXTINF" not in delivery.playlist("a") and "ENDLIST" not in delivery.playlist("a")
    assert manager.push("a", [(g, ref(g)) for g in range(50)], 0) == 50
    assert manager.push("a", [(g, ref(g)) for g in range(40, 60)], 1) == 10  # ten were there already
    with pytest.raises(service.SpecRejected):
        manager.push("a", [(60, ref(10**9))], 2)
    before = delivery.playlist("a")
    assert before.count("#EXTINF") == 1 and manager.status("a") == {"frames": 60, "prefix": 60, "listed": 1, "ended": False}
    with pytest.raises(KeyError):
        delivery.segment("a", 1)
    packets = delivery.segment("a", 0)
    assert [i for i, _ in codec.decode(packets)] == list(range(48))
    assert delivery.segment("a", 0) == packets and (delivery.hits, delivery.requests) == (1, 3)
    manager.terminate("a")
    with pytest.raises(service.SpecRejected):
        manager.push("a", [(60, ref(60))], 3)
    after = delivery.playlist("a")
    assert after.startswith(before) and after.endswith("#EXT-X-ENDLIST\n") and after.count("#EXTINF") == 2
    assert len(delivery.segment("a", 1)) == 12
    manager.delete("a")
    assert manager.create("a", 16, 16)


def test_restart_and_clean_up(spark, service_parts, tmp_path):
    manager, delivery = service_parts
    place = "file://" + str(tmp_path / "store")
    first = service.Manager(service.Store(spark, place), manager.sources)
    first.create("kept", 16, 16)
    first.push("kept", [(g, ref(g)) for g in range(50)], 0)
    first.push("kept", [(g, ref(g)) for g in range(50)], 1)  # nothing new
    first.create("empty", 16, 16, fps=(30, 1))
    again = service.Manager(service.Store(spark, place), manager.sources)  # as after a restart
    assert again.status("kept") == first.status("kept") == {"frames": 50, "prefix": 50, "listed": 1, "ended": False}
    assert again.store.state["empty"]["fps"] == (30, 1)
    assert again.push("kept", [(g, ref(g)) for g in range(48, 60)], 2) == 10
    again.terminate("kept")
    served = service.Delivery(service.Manager(service.Store(spark, place), manager.sources), delivery.gops)
    assert served.playlist("kept").endswith("#EXT-X-ENDLIST\n") and len(served.segment("kept", 1)) == 12
    store = service.Store(spark, place)
    store.files.write(f"{place}/specs/spec_id=lost/x", "left over")
    store.save("empty", now=0.0)
    assert store.clean(3600) == ["empty"] and store.files.names(f"{place}/specs") == ["spec_id=kept"]
    service.Manager(store, manager.sources).delete("kept")
    assert store.files.names(f"{place}/specs") == store.files.names(f"{place}/state") == [] and not service.Store(spark, place).state


def test_segments_through_the_block_cache(spark, service_parts, tmp_path):
    from reelspark.sources.files import BlockCache, ClipFile, Files

    manager, delivery = service_parts
    files, path = Files(spark), "file://" + str(tmp_path / "main.clip")
    rows = [r.asDict(recursive=True) for r in delivery.gops.where("source_id = 'main' AND gop_id < 5").collect()]
    ClipFile.write(files, path, rows)
    cache = BlockCache(files, 4096, 64)
    clip = ClipFile(cache, path)
    for g in rows:
        assert [(p["idx"], bytes(p["bytes"])) for p in clip.packets(g["gop_id"])] == [(p["idx"], bytes(p["bytes"])) for p in g["packets"]]
    whole = files.read_bytes(path)
    assert all(cache.read(path, a, n) == whole[a : a + n] for a, n in ((0, 1), (4095, 2), (100, 9000), (len(whole) - 3, 10), (5, 0)))
    manager.create("cached", 16, 16)
    manager.push("cached", [(g, ref(g)) for g in range(96)], 0)
    one, two = service.Delivery(manager, delivery.gops), service.Delivery(manager, {"main": clip})
    before = cache.hits
    assert one.segment("cached", 0) == two.segment("cached", 0) and one.segment("cached", 1) == two.segment("cached", 1)
    assert cache.hits > before and len(cache.held) <= 64


def test_rules_of_requests(spark):
    cases = {"Show me the speed over the drive": ("telemetry overlay", ""), "sort the frames by colour": ("hue order", ""), "draw boxes around people": ("boxes of class", ""), "find where she says river": ("search clip", "river"), 'clips with "Harbour" please': ("search clip", "harbour"), "ok": ("search clip", ""), "moments of happiness": ("search clip", "moments")}
    rows = spark.createDataFrame([(i, 0, t) for i, t in enumerate(cases)], "conv_id int, turn int, text string")
    got = {r["conv_id"]: (r["intent"], r["word"]) for r in dialog.intents(rows).collect()}
    for i, (text, want) in enumerate(cases.items()):
        assert got[i] == dialog.intent_of(text) == want


def test_show_me_end_to_end(service_parts):
    manager, delivery = service_parts
    clips = {"main": ClipMeta("main", 16, 16, "yuv420p", 1500)}
    answer = dialog.show_me("x" * 4, manager, [(10, 30), (500, 25)], clips)
    assert answer.intent == "search clip" and manager.status(answer.spec_id) == {"frames": 55, "prefix": 55, "listed": 2, "ended": True}
    assert len(delivery.segment(answer.spec_id, 0)) == 48 and len(delivery.segment(answer.spec_id, 1)) == 7


@pytest.mark.parametrize("source", ["def main(im, rows):\n    open('/etc/passwd')\n", "import os\ndef main(im, rows):\n    pass\n", "def main(im, rows):\n    1 / 0\n"])
def test_sandbox_refuses(source):
    with pytest.raises(dialog.ScriptFailed):
        dialog.run_sandboxed(source, [], {})


def test_sandbox_time_limit():
    with pytest.raises(dialog.ScriptFailed, match="time limit"):
        dialog.run_sandboxed("def main(im, rows):\n    while True:\n        pass\n", [], {}, seconds=0.5)


def test_late_pushes_within_the_watermark_all_count(spark, sf_dir):
    from reelspark.registry import QUERIES, load

    load()
    rows = QUERIES["st_watermark_late"](spark, sf_dir).collect()
    assert rows and len({r["start_us"] for r in rows}) == len(rows)
    out = {r["mode"]: r for r in QUERIES["st_outputs"](spark, sf_dir).collect()}
    assert out["complete"]["total"] == spark.read.parquet(f"{sf_dir}/events.parquet").count()
    assert out["append"]["total"] <= out["complete"]["total"] <= out["update"]["total"]


def test_partitions_keep_generation_order(spark, sf_dir):
    from reelspark.registry import QUERIES, load

    load()
    parts: dict = {}
    for r in QUERIES["sort_within"](spark, sf_dir).collect():
        parts.setdefault(r["part"], []).append((r["seg"], r["gen"]))
    assert all(v == sorted(v) for v in parts.values())


def test_sketches_are_near(spark, sf_dir):
    from reelspark.registry import QUERIES, load

    load()
    for r in QUERIES["agg_approx"](spark, sf_dir).collect():
        assert abs(r["users_hll"] - r["users"]) <= max(1, 0.1 * r["users"]) and abs(r["users_sketch"] - r["users"]) <= max(1, 0.05 * r["users"])
        assert abs(r["median_approx"] - r["median"]) <= 1


def test_playback_over_http(service_parts):
    import threading
    import urllib.error
    import urllib.request

    from reelspark.vod import http

    manager, delivery = service_parts
    manager.create("web", 16, 16)
    manager.push("web", [(g, ref(g)) for g in range(60)], 0)
    manager.terminate("web")
    s = http.server(delivery)
    threading.Thread(target=s.serve_forever, daemon=True).start()
    try:
        base = f"http://127.0.0.1:{s.server_address[1]}"
        get = lambda path: urllib.request.urlopen(base + path, timeout=60).read()
        uris = [x for x in get("/web/playlist.m3u8").decode().splitlines() if x.endswith(".seg")]
        assert uris == ["web/0.seg", "web/1.seg"]
        frames = [i for u in uris for i, _ in codec.decode(http.unpacked(get("/" + u)))]
        assert frames == list(range(60))
        for missing in ("/web/2.seg", "/nobody/playlist.m3u8", "/"):
            with pytest.raises(urllib.error.HTTPError):
                get(missing)
    finally:
        s.shutdown()
