"""Tables, derived road networks and a replayed traffic source."""
