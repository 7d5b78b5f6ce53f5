"""What the joins are measured against."""
