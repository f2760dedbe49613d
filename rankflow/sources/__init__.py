"""Where graphs come from and where snapshots and ranks are kept."""
