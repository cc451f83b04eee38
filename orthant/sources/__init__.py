"""Tables and files as matrices in coordinate form."""
