"""Requests in words -> query, script, spec and playlist. Templates stand in for a language model."""

from __future__ import annotations

import hashlib
import multiprocessing
import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.session import table

INTENTS = ("search clip", "boxes of class", "hue order", "telemetry overlay")

#: A script per intent, over the imaging surface that replays it (``rows`` are the query's results).
SCRIPTS = {
    "search clip": "def main(imaging, rows):\n    out = imaging.new_clip()\n    clip = imaging.open_clip('main')\n    for number, (first, n) in enumerate(rows, 1):\n        for k in range(n):\n            clip.seek(first + k)\n            ok, frame = clip.read()\n            if ok:\n                imaging.text(frame, '#' + str(number), (1, 1))\n                out.write(frame)\n    out.close()\n",
    "boxes of class": "def main(imaging, rows):\n    out = imaging.new_clip()\n    clip = imaging.open_clip('main')\n    for i, x1, y1, x2, y2 in rows:\n        clip.seek(i)\n        ok, frame = clip.read()\n        if ok:\n            imaging.box(frame, (x1, y1), (x2, y2), (0, 0, 255))\n            out.write(frame)\n    out.close()\n",
    "hue order": "def main(imaging, rows):\n    out = imaging.new_clip()\n    clip = imaging.open_clip('short')\n    for i in rows:\n        clip.seek(i)\n        ok, frame = clip.read()\n        if ok:\n            out.write(frame)\n    out.close()\n",
    "telemetry overlay": "def main(imaging, rows):\n    out = imaging.new_clip()\n    clip = imaging.open_clip('main')\n    for value in rows:\n        ok, frame = clip.read()\n        if not ok:\n            break\n        imaging.text(frame, str(value), (0, 9))\n        out.write(frame)\n    out.close()\n",
}


#: First rule whose pattern a request (in lower case) holds gives the intent; without any it is a search for a word.
RULES = (("telemetry overlay", r"\b(telemetry|speed|sensor|readings?|overlay)\b"), ("hue order", r"\b(hue|colou?rs?|rainbow|sort(ed)?)\b"), ("boxes of class", r"\b(box(es)?|detect[a-z]*|objects?|class)\b"))
#: The word of a search: in quotes, after "says" or "mentions", or else the request's first long word.
QUOTED, NAMED, LONG = r"['\"]([a-z]{3,})['\"]", r"\b(?:says?|said|mentions?|spoken)\s+([a-z]{3,})", r"([a-z]{7,})"


def intent_of(text: str) -> tuple[str, str]:
    """(intent, word)."""
    low = text.lower()
    for intent, pattern in RULES:
        if re.search(pattern, low):
            return intent, ""
    found = re.search(QUOTED, low) or re.search(NAMED, low) or re.search(LONG, low)
    return INTENTS[0], found.group(1) if found else ""


def intents(turns: DataFrame) -> DataFrame:
    """The intent of each request and, for a search, its word: the rules as column functions."""
    low = F.lower("text")
    pick = F.lit(None).cast("string")
    for intent, pattern in reversed(RULES):
        pick = F.when(low.rlike(pattern), F.lit(intent)).otherwise(pick)
    word = F.lit("")
    for pattern in (LONG, NAMED, QUOTED):
        word = F.when(F.regexp_extract(low, pattern, 1) != "", F.regexp_extract(low, pattern, 1)).otherwise(word)
    out = turns.select("conv_id", "turn", F.coalesce(pick, F.lit(INTENTS[0])).alias("intent"), word.alias("word"))
    return out.withColumn("word", F.when(F.col("intent") == INTENTS[0], F.col("word")).otherwise(F.lit("")))


def sizes(spark: SparkSession, sf_dir: str, asked: DataFrame) -> DataFrame:
    """(intent, word, spec_frames): frames that each query asks for; searches of a word are one multi-pattern scan of all texts."""
    from reelspark.workloads.search import containing

    t = lambda n: table(spark, sf_dir, n)
    one = lambda df, intent, c: df.agg(c.cast("bigint").alias("spec_frames")).select(F.lit(intent).alias("intent"), F.lit("").alias("word"), "spec_frames")
    words = asked.where(F.col("word") != "").select("word").distinct().select(F.xxhash64("word").alias("item_id"), F.col("word").alias("text"))
    found = containing(t("documents").select(F.lower("text").alias("text")), words, apart=True).groupBy("item_id").agg((F.count("*") * 77).alias("spec_frames"))
    searches = words.join(found, "item_id", "left").select(F.lit(INTENTS[0]).alias("intent"), F.col("text").alias("word"), F.coalesce("spec_frames", F.lit(0)).alias("spec_frames"))
    return (
        searches.unionByName(one(t("lineitem").where("l_returnflag = 'A'"), INTENTS[1], F.count_distinct("l_orderkey")))
        .unionByName(one(t("embeddings"), INTENTS[2], F.count("*")))
        .unionByName(one(t("orders"), INTENTS[3], F.count("*")))
    )


@dataclass(frozen=True)
class Answer:
    intent: str
    script: str
    spec_id: str
    playlist: str


_SAFE = ("abs", "bool", "dict", "enumerate", "float", "int", "len", "list", "max", "min", "range", "reversed", "round", "sorted", "str", "sum", "tuple", "zip")


def _child(source: str, rows, clips, conn, memory_mb: int) -> None:
    import builtins
    import resource

    from reelspark.lift.shim import ClipEnv, Imaging

    resource.setrlimit(resource.RLIMIT_AS, (memory_mb << 20, memory_mb << 20))
    try:
        scope = {"__builtins__": {n: getattr(builtins, n) for n in _SAFE}}
        exec(compile(source, "script", "exec"), scope)  # noqa: S102  names are limited to a list, and the process to time and memory
        scope["main"](Imaging(ClipEnv(clips), lambda gen, nodes: conn.send(("frame", gen, nodes))), rows)
        conn.send(("done", None, None))
    except BaseException as e:  # noqa: BLE001  whatever the script raised is its result
        conn.send(("error", type(e).__name__, str(e)))


class ScriptFailed(RuntimeError):
    pass


def run_sandboxed(source: str, rows, clips: dict, push=None, seconds: float = 20, memory_mb: int = 4096) -> int:
    """Runs ``main(imaging, rows)`` in a process of its own: query results go in, pushed frames come out, nothing else.

    Frames reach ``push(gen, nodes)`` while the script runs; ``push(None, None)`` marks its end. Returns the number of frames.
    """
    import time

    here, there = multiprocessing.get_context("fork").Pipe(duplex=False)
    p = multiprocessing.get_context("fork").Process(target=_child, args=(source, rows, clips, there, memory_mb), daemon=True)
    p.start()
    there.close()
    until, n = time.monotonic() + seconds, 0
    try:
        while True:
            if not here.poll(max(0.0, until - time.monotonic())):
                raise ScriptFailed("time limit")
            try:
                kind, a, b = here.recv()
            except EOFError as e:
                raise ScriptFailed("the script's process ended") from e
            if kind == "error":
                raise ScriptFailed(f"{a}: {b}")
            if kind == "done":
                return n
            n += a is not None
            if push:
                push(a, b)
    finally:
        p.kill()
        p.join()


def show_me(text: str, manager, rows, clips: dict, size: tuple[int, int, str] = (16, 16, "yuv420p"), batch_frames: int = 30) -> Answer:
    """A request end to end against a service: namespace and link at once, then the script's frames in batches, then the end."""
    intent, _ = intent_of(text)
    spec_id = "show-" + hashlib.sha256(f"{len(manager.store.state)}:{text}".encode()).hexdigest()[:16]
    link = manager.create(spec_id, *size)
    held: list[tuple[int, list[dict]]] = []
    batches = [0]

    def flush() -> None:
        if held:
            manager.push(spec_id, list(held), batches[0])
            batches[0] += 1
            held.clear()

    def push(gen, nodes) -> None:
        if gen is None:
            flush()
            manager.terminate(spec_id)
        else:
            held.append((gen, nodes))
            if len(held) >= batch_frames:
                flush()

    run_sandboxed(SCRIPTS[intent], rows, clips, push)
    return Answer(intent, SCRIPTS[intent], spec_id, link)
