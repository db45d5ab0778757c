"""cubecast.operators"""
