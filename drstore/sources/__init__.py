"""Tables in, encoded stores out and back."""
