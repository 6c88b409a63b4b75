"""Column layouts of the tables that operators exchange; indices start at 0."""

FRAMES = "video_id string, t int, h int, w int, ch int, px array<float>"
SERIES = "series_id string, t int, v array<double>"
PIXELS = "video_id string, t int, y int, x int, ch int, val double"
TILES = "video_id string, t int, tile int, px array<float>"
PAIRS = "video_id string, i int, j int, d2 double"
PHASE = "video_id string, i int, phi double, phi_u double"
BARS = "video_id string, dim int, birth double, death double, persistence double"
MODES = "video_id string, rank int, lambda double, vec array<double>, zero_cross int"
VOTES = "video_id string, j int, i int, a int, b int, frac double, offset double"
TEMPLATE = "video_id string, j int, theta double, tile int, px array<float>, n_votes long"
RUN = (
    "video_id string, n int, period double, d int, sigma double, alpha double, kernel string, coeff int, k double, loop_ratio double,"
    " n_components int, fallback boolean, cover_radius double"
)
ERROR = "video_id string, corruption string, level double, trial int, windowed boolean, alpha double, err_deg double"


class BadInput(ValueError):
    """A recording that an operator cannot take; the message says why."""


def names(layout: str) -> list[str]:
    return [part.split()[0] for part in layout.split(", ")]
