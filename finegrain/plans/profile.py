"""Constants of the modelled network and cores."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class NetworkProfile:
    """Nanoseconds. ``hop_ns`` replaces the topology's path where it is set; ``tail_share`` of messages take ``tail_ns`` more."""

    link_ns: float = 43.0
    switch_ns: float = 263.0
    leaf_nodes: int = 64
    first_receive_ns: float = 8.0
    next_receive_ns: float = 6.22
    send_ns: float = 4.0
    scan_ns: float = 2.2
    sort_ns: float = 2.93
    hop_ns: float | None = None
    multicast: bool = True
    tail_share: float = 0.01
    tail_ns: float = 0.0
    #: bytes of a key with its origin, of a pivot, of a record
    key_bytes: int = 16
    pivot_bytes: int = 16
    record_bytes: int = 104

    @property
    def near_ns(self) -> float:
        """One way inside a leaf."""
        return self.hop_ns if self.hop_ns is not None else 2 * self.link_ns + self.switch_ns

    @property
    def far_ns(self) -> float:
        """One way across leaves."""
        return self.hop_ns if self.hop_ns is not None else 4 * self.link_ns + 3 * self.switch_ns

    def hop(self, nodes: int) -> float:
        return self.near_ns if nodes <= self.leaf_nodes else self.far_ns

    def receive(self, messages: float) -> float:
        return 0.0 if messages <= 0 else self.first_receive_ns + (messages - 1) * self.next_receive_ns

    def with_(self, **changes) -> NetworkProfile:
        return replace(self, **changes)


#: A hop that gives the published merge-tree optimum, and end-host stacks by their median wire-to-wire latency.
PRESETS = {
    "simulated": NetworkProfile(),
    "tree_merge_published": NetworkProfile(hop_ns=185.0),
    "software_stack": NetworkProfile(hop_ns=850.0),
    "integrated_nic": NetworkProfile(hop_ns=100.0),
    "register_nic": NetworkProfile(hop_ns=69.0),
}
