"""Front (skyline) operators over any DataFrame."""
