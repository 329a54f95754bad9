"""Where nodes and pairs come from and go to."""
