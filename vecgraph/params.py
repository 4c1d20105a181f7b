"""Parameters of an index, and the two presets."""

from __future__ import annotations

from dataclasses import asdict, dataclass, replace


@dataclass(frozen=True)
class Params:
    """Constants of one index; every method variant is a setting of its flags."""

    dim: int
    metric: str = "l2"  # or "cosine"
    m_links: int = 16  # out-edges of a new node; the cap of a node is twice that
    ef_build: int = 64
    work: int = 16  # size of the working set and of each ring
    blocks: int = 8  # parts that a vector is cut into
    refs_per_block: int = 32
    seed: int = 17
    gate: bool = True
    rings: bool = True
    screen: bool = True
    gate_in_build: bool = True  # False: the test only speeds up searches of a finished graph
    scope: str = "visited"  # whom the screen looks at: all visited nodes, or "out": the new node's out-neighbours only
    threshold: str = "work"  # the gate's rim: of the working set, or of the whole "queue"
    layers: bool = False  # layered entry descent
    alpha: float = 1.0  # pruning ratio
    half: bool = False  # two-byte floats for stored vectors
    max_batch: int = 256
    verify_every: int = 1  # build batches between two verifications of pending edges
    shard_bytes: int = 128 << 20  # of one shard's vectors and links
    shard_size: int = 0  # vectors of one shard; 0: as many as fit the bytes
    preset: str = "custom"

    def __post_init__(self) -> None:
        if self.dim < 1 or self.blocks < 1 or self.refs_per_block < 2 or self.refs_per_block > 256:
            raise ValueError("dim and blocks must be positive, refs_per_block within 2..256")
        if self.metric not in ("l2", "cosine") or self.scope not in ("visited", "out"):
            raise ValueError("metric is l2 or cosine, scope is visited or out")

    @property
    def cap(self) -> int:
        return 2 * self.m_links

    @property
    def padded(self) -> int:
        """The dimension with zeros added so that it divides into equal blocks; distances stay."""
        return -(-self.dim // self.blocks) * self.blocks

    @property
    def node_bytes(self) -> int:
        """Bytes of a node with all its links in memory."""
        return 4 * self.padded + self.cap * (4 * 4 + 1 + self.blocks) + 12

    @property
    def per_shard(self) -> int:
        """Vectors of one shard at most."""
        return self.shard_size or max(64, self.shard_bytes // self.node_bytes)

    def but(self, **changes) -> Params:
        return replace(self, **changes)

    def as_dict(self) -> dict:
        return asdict(self)

    @staticmethod
    def throughput(dim: int, **changes) -> Params:
        """Many queries a second: more links, longer codes."""
        blocks = max(b for b in range(1, min(32, max(1, dim // 4)) + 1) if -(-dim // b) * b - dim < b)
        return Params(dim=dim, m_links=32, ef_build=128, work=32, blocks=blocks, refs_per_block=64, preset="throughput").but(**changes)

    @staticmethod
    def compact(dim: int, **changes) -> Params:
        """Fast build and small index: few links, short codes, two-byte vectors."""
        return Params(dim=dim, m_links=12, ef_build=64, work=24, blocks=8, refs_per_block=16, half=True, preset="compact").but(**changes)
