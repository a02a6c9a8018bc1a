"""Edge streams and directory maintenance."""
