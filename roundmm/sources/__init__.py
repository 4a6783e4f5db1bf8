"""Where matrices come from and go to."""
