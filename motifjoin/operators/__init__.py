"""The joins and the indices they run on."""
