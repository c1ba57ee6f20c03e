"""Delivery over local HTTP: a playlist and its segments. Management calls stay functions (`vod.service.Manager`)."""

from __future__ import annotations

import json
import re
from http.server import BaseHTTPRequestHandler, ThreadingHTTPServer

from reelspark.vod.service import Delivery


def packed(packets: list[dict]) -> bytes:
    """A segment as one body: a JSON line that lists the packets, then their bytes."""
    head = [{"dpos": p["dpos"], "idx": p["idx"], "kind": p["kind"], "size": len(p["bytes"])} for p in packets]
    return json.dumps(head).encode() + b"\n" + b"".join(p["bytes"] for p in packets)


def unpacked(body: bytes) -> list[dict]:
    head, _, data = body.partition(b"\n")
    out, at = [], 0
    for p in json.loads(head):
        out.append({"dpos": p["dpos"], "idx": p["idx"], "kind": p["kind"], "bytes": data[at : at + p["size"]]})
        at += p["size"]
    return out


def server(delivery: Delivery, host: str = "127.0.0.1", port: int = 0) -> ThreadingHTTPServer:
    """Not yet started; ``serve_forever`` in a thread of its own, ``shutdown`` ends it."""

    class Handler(BaseHTTPRequestHandler):
        def do_GET(self) -> None:
            try:
                if m := re.fullmatch(r"/([\w-]+)/playlist\.m3u8", self.path):
                    kind, body = "application/vnd.apple.mpegurl", delivery.playlist(m[1]).encode()
                elif m := re.fullmatch(r"/([\w-]+)/(\d+)\.seg", self.path):
                    kind, body = "application/octet-stream", packed(delivery.segment(m[1], int(m[2])))
                else:
                    raise KeyError(self.path)
            except KeyError:
                self.send_error(404)
                return
            self.send_response(200)
            self.send_header("Content-Type", kind)
            self.send_header("Content-Length", str(len(body)))
            self.end_headers()
            self.wfile.write(body)

        def log_message(self, *args) -> None:
            pass

    return ThreadingHTTPServer((host, port), Handler)
