"""Tables as particles, generated particles, snapshots and sinks."""
