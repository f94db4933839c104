"""Tables, policies and snapshots read and written."""
