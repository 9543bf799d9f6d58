"""Where stores and key lists are read from and written to."""
