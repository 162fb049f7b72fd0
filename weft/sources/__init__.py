"""Where words come from and schemas go to."""
