"""Parameters of a maintained view; all of them are public."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    eps: float = 1.5
    omega: int = 1
    budget: int = 10
    interval: int = 10
    theta: float = 30.0
    purge_every: int = 2000
    purge_size: int = 15
    #: Padded size of a step's derived rows: 'omega' slots for each new or active private row (which is every row that
    #: the scanning join passes), or 'budget' slots for each row of the step's own upload.
    pad_rule: str = "omega"
    #: Public sizes to which every upload of the left and the right side is padded; the right one of a public side is
    #: not used. Without them the largest upload counts as the size that was declared.
    batch_cap: tuple[int, int] | None = None
    seed: str = "7"
    #: False: hash words from ``seed`` (tests and twins); True: words from the system, stored before they are used.
    system_noise: bool = False
    #: Whether a purge sets the counter of new rows to 0, as a release does.
    purge_resets_counter: bool = False
    #: 'protocol': release noise of the threshold rule has scale 2b/eps; 'mechanism': 4b/eps.
    scale_release: str = "protocol"

    def __post_init__(self) -> None:
        if self.eps <= 0:
            raise ValueError("eps must be positive")
        if self.omega < 1 or self.budget < self.omega:
            raise ValueError("a row needs budget for one use at least: budget >= omega >= 1")
        if self.interval < 1 or self.purge_every < 1 or self.purge_size < 0 or self.theta < 0:
            raise ValueError("interval and purge_every start at 1, purge_size and theta at 0")
        if self.pad_rule not in ("omega", "budget"):
            raise ValueError("pad_rule is omega or budget")
        if self.batch_cap is not None and (len(self.batch_cap) != 2 or min(self.batch_cap) < 1):
            raise ValueError("batch_cap is two sizes of at least 1")
        if self.scale_release not in ("protocol", "mechanism"):
            raise ValueError("scale_release is protocol or mechanism")

    @property
    def horizon(self) -> int:
        """Steps in which a row may be used: each use costs omega, whatever it yields."""
        return self.budget // self.omega

    def but(self, **changes) -> Params:
        return replace(self, **changes)
