import io
import struct
import zipfile
import zlib

from ctxloom.llm import media


def png():
    chunk = lambda kind, data: struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", 1, 1, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(b"\0\0")) + chunk(b"IEND", b"")


def crc(data, bits, polynomial):
    c = 0
    for x in data:
        c ^= x << (bits - 8)
        for _ in range(8):
            c = (c << 1 ^ polynomial if c >> (bits - 1) else c << 1) & ((1 << bits) - 1)
    return c


def flac(frames=3):
    info = struct.pack(">HH", 192, 192) + bytes(6) + ((44100 << 44) | (15 << 36) | 192 * frames).to_bytes(8, "big") + bytes(16)
    out = b"fLaC\x80" + (34).to_bytes(3, "big") + info
    for i in range(frames):
        head = bytes([0xFF, 0xF8, 0x19, 0x08, i])
        frame = head + bytes([crc(head, 8, 0x07)]) + bytes([0, 1 + i, 7])
        out += frame + crc(frame, 16, 0x8005).to_bytes(2, "big")
    return out


def test_media_inside_media():
    p, stored = png(), io.BytesIO()
    with zipfile.ZipFile(stored, "w") as z:
        z.writestr("a.png", p)
    body = b"%PDF-1.4\n1 0 obj\nstream\n" + p + b"\nendobj\n"
    pdf = body + b"xref\n0 1\ntrailer<<>>\nstartxref\n%d\n%%%%EOF" % len(body)
    for outer, kind in ((pdf, "application/pdf"), (stored.getvalue(), "application/zip"), (media.wav_of(p + bytes(len(p) % 2)), "audio/wav")):
        assert [(h.kind, h.parent) for h in media.sniff(outer)] == [(kind, -1), ("image/png", 0)]
        inner = media.sniff(outer)[1]
        assert outer[inner.start : inner.start + inner.length] == p


def test_flac_ends_at_its_last_frame():
    f, p = flac(), png()
    assert [(h.kind, h.start, h.length) for h in media.sniff(f + p)] == [("audio/flac", 0, len(f)), ("image/png", len(f), len(p))]
    assert media.sniff(f[:-1]) == [] and media.sniff(f[:-12]) == []
