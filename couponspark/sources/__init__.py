"""Where ids and sketches come from and go to."""
