"""Row types that the stages hand on."""

DETECTION = "scene int, clip bigint, t bigint, obj bigint, category string, x double, y double, w double, h double, score double"
TRACK_POINT = DETECTION + ", track_id bigint"
WINDOW = "px int, py int, pw int, ph int, sec double"
WIDTH, HEIGHT, CELL, FPS, FRAMES = 640, 384, 32, 8, 480
COLUMNS, ROWS = WIDTH // CELL, HEIGHT // CELL
SPLITS = ("train", "val", "test")
#: Detector cost in seconds: base + unit * width * height.
COST = {"one_stage": (0.002, 3.2e-8), "two_stage": (0.010, 1.2e-7)}
PROXY_COST = (0.0002, 2e-9)
#: Proxy input sizes, cells of 32 px each.
PROXY_SIZES = [(640, 384), (512, 320), (416, 256), (224, 128), (160, 96)]
#: Misses and spurious boxes of the simulated detectors, per mille at full resolution.
MISSES = {"one_stage": 80, "two_stage": 40}
SPURIOUS = {"one_stage": 15, "two_stage": 5}


def seconds(arch: str, w: float, h: float) -> float:
    base, unit = COST[arch]
    return base + unit * w * h


def window_sizes(extra: list[tuple[int, int]], arch: str = "one_stage", scale: float = 1.0) -> list[tuple[int, int, float]]:
    """(w, h, sec) with the whole frame first; seconds follow a detector resolution of ``scale`` times the frame's."""
    sizes = [(WIDTH, HEIGHT), *[s for s in extra if s != (WIDTH, HEIGHT)]]
    return [(w, h, seconds(arch, w * scale, h * scale)) for w, h in sizes]
