"""What a physical plan must look like."""
