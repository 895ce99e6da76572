"""Tables and files as event streams, planted overlays, the simulator as a data source."""
