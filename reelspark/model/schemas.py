"""Row shapes at module boundaries, as DDL.

A frame expression is one row: its nodes in post-order, kids before parents, the root last.
A node has an operation, the positions of its kid nodes, integer constants and one string constant.
"""

NODE = "struct<op:string,kids:array<int>,ints:array<bigint>,text:string>"
SPEC = f"spec_id string, gen bigint, seg bigint, nodes array<{NODE}>"
SOURCES = "source_id string, width int, height int, fmt string, n_frames bigint, fps_num int, fps_den int, gop_len int"
PACKET = "struct<dpos:int,idx:bigint,kind:string,bytes:binary>"
GOPS = f"source_id string, gop_id bigint, first_idx bigint, n int, packets array<{PACKET}>"
RENDERED = "spec_id string, gen bigint, w int, h int, fmt string, md5 string"
STATS = "frames_decoded bigint, gop_opens bigint, abandons bigint, evictions bigint, drops bigint, stalls bigint, peak_pool bigint, ticks bigint"
#: Planes of a format as divisors of width and height, and channels interleaved in a plane.
FORMATS = {"gray8": [(1, 1, 1)], "yuv420p": [(1, 1, 1), (2, 2, 1), (2, 2, 1)], "bgr24": [(1, 1, 3)], "rgb24": [(1, 1, 3)]}
SEGMENT_SECONDS = 2


def frame_bytes(w: int, h: int, fmt: str) -> int:
    return sum(-(-w // a) * -(-h // b) * c for a, b, c in FORMATS[fmt])


def segment_frames(fps_num: int, fps_den: int = 1, seconds: int = SEGMENT_SECONDS) -> int:
    """Frames of a segment: rounded to whole frames, at least one."""
    return max(1, (seconds * fps_num + fps_den // 2) // fps_den)
