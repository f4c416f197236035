"""Tables, device splits and features."""
