"""Windows over streams of events with uncertain time."""
