"""Parameters of the spectral codec."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Constants:
    """What turns the error bound into parameters: eps_f = eps / a, b_s = b * eps + c, r_ret = d / sqrt(eps).
    The published values are not in the text; plans/calibrate.py finds them on a sample of a set's tracks."""

    a: float = 0.6
    b: float = 0.0
    c: float = 16.0
    d: float = 10.0


#: by number, as a container's header names them
CONSTANTS: dict[int, Constants] = {
    0: Constants(), 1: Constants(c=32.0), 2: Constants(a=0.5),
    # found by plans/calibrate.py on a hash sample of the tracks of sf0.01
    3: Constants(a=0.8, b=0.04, c=4.0, d=5.86), 4: Constants(a=0.7, b=0.08, c=6.0, d=2.93), 5: Constants(a=0.7, b=0.0, c=16.0, d=0.192),
    6: Constants(a=0.7, b=0.32, c=8.0, d=1.58), 7: Constants(a=0.8, b=0.16, c=4.0, d=2.93),
}
#: set and dimension -> the number found for it
OF_FIXTURE = {"ev_user:2": 3, "ev_type_smooth:2": 4, "emb_cum:2": 5, "li_supp_smooth:3": 6, "li_supp:3": 7}


@dataclass(frozen=True)
class CodecParams:
    eps: float
    eps_f: float
    b_s: int
    r_ret: float
    eps_p: float
    eps_t: int = 1  # microseconds
    v_max: float | None = None  # distance a second
    gap_mean: str = "inclusive"
    default_dt: int | None = None
    dt_scale: float = 1.0  # of the common interval's rule
    l: int = 2  # noqa: E741  chunk length of all but the coefficients
    l_freq: int = 1
    zero_free: bool = True
    ends: str = "closed"
    validate: bool = True
    positions: bool = False  # transform positions instead of velocities
    blocks: bool = True
    integer_input: bool = False  # whole numbers, kept exactly: no transform and no quantizer
    constants: int = 0

    def with_(self, **changes) -> CodecParams:
        return replace(self, **changes)

    def kept(self, length: int) -> int:
        """Coefficients that survive truncation in a block of this length, the unstored first one included."""
        return max(1, min(length, math.floor(length * self.r_ret + 0.5)))


#: what a decoder needs to know; the rest steers the encoder alone
DECODER = ("eps", "eps_t", "eps_f", "b_s", "eps_p", "l", "l_freq", "zero_free", "positions", "blocks", "integer_input")


def derive(eps: float, dim: int = 2, constants: int = 0, **changes) -> CodecParams:
    """Parameters for an error bound: the same for encoder and decoder, so a container holds only what was changed.

    `dim` is checked and no more: which constants suit a set and its dimension is decided by their number."""
    if dim < 1 or not eps > 0:
        raise ValueError(f"no bound {eps} in {dim} dimensions")
    k = CONSTANTS[constants]
    made = CodecParams(
        eps=eps, eps_f=eps / k.a, b_s=max(1, math.floor(k.b * eps + k.c + 0.5)), r_ret=min(1.0, k.d / math.sqrt(eps)), eps_p=0.5 * eps, constants=constants
    )
    return made.with_(**changes)
