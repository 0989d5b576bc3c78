"""Update streams."""
