"""What the two-phase join is measured against."""
