"""Where sequences, frames and tables come from and go to."""
